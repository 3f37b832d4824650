"""Exact temporal analytics over interval histories, on Spark."""
