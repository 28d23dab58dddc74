"""Training workloads on the given tables."""
