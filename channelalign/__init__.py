"""Alignment of entities across event streams from the timing of their activity, on Spark DataFrames."""
