"""Threshold-aware inverted-file candidate retrieval on Spark DataFrames."""
