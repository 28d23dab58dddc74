"""Gradient sparsification as Spark plans."""
