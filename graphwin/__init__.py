"""Vertex-window analytics on Spark: windows over graph structure, reusable window indices, baselines and measures."""
