"""Whole runs, measures and experiments, composed of operators."""
