"""Fact tables with their dimensions, and file formats."""
