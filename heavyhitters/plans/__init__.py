"""End-to-end methods, invariant checks and experiments."""
