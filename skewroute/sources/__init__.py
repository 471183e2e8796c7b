"""Keyed message streams from tables and generators."""
