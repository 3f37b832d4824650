"""Planning, running, sizing and measuring."""
