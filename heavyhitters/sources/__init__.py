"""Workloads over the given tables, synthetic generators, and summary stores."""
