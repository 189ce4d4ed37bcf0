"""Compact, three-dimensional indexing of point clouds on Spark."""
