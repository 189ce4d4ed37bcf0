"""Trees, leaves, queries, baselines and measures over point clouds."""
