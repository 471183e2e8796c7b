"""Skew-aware routing of keyed streams for Spark."""
