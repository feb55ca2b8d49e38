"""Frequent-item analytics for Spark: mergeable counter summaries, baselines, measures."""
