"""Exploration of one wide table through all of its three-way interactions, on Spark."""
