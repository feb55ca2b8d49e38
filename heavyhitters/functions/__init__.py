"""Accuracy measures, the cost model and user-defined functions."""
