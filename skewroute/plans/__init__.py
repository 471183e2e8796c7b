"""Experiment grids, the SQL surface and the query catalogue."""
