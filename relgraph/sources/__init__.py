"""Readers, writers, and the graphs that the given tables hold."""
