"""The experiments, on the given tables."""
