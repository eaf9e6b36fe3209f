"""Interacting-particle tissues, and the balancing of the work they create, on Spark DataFrames."""
