"""Metric similarity joins on Spark: pivots by fitted distributions, balanced regions, exact results."""
