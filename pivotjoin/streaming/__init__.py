"""Joins and measures over streams."""
