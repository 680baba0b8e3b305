"""Planning on the driver: who owns which triple, and which strategy is cheapest."""
