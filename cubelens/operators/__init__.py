"""Operators of the method: ranks, bins, cubes, images, recommendation."""
