"""Mergeable distinct counting for Spark: sketches, baselines, bounds and measures."""
