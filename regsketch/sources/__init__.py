"""Readers of the given tables and the store of sketches."""
