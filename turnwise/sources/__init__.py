"""Readers, sinks and the graphs built from the given tables."""
