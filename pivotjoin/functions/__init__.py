"""Distances, distribution families, numerics and filters."""
