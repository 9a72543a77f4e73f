"""Provable windowed queries over append-only time series, on Spark DataFrames."""
