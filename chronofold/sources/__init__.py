"""Histories, layouts, readers and writers."""
