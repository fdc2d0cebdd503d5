"""Joins and densities over streams."""
