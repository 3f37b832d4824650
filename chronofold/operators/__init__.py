"""Temporal operators and their merges."""
