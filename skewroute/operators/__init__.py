"""Routing, head detection, measures and worker-side aggregation."""
