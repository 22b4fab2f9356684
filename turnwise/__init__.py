"""Skew-aware transposition of graphs and sparse matrices on Spark."""
