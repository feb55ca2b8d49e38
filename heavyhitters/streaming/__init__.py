"""Frequent items over streams."""
