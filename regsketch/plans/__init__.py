"""Sketch parameters, plan shapes and the catalogue of queries."""
