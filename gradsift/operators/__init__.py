"""The steps of an iteration, each from DataFrames to a DataFrame."""
