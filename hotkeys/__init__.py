"""Frequent elements for Spark: owner-split summaries, baselines, measures and workloads."""
