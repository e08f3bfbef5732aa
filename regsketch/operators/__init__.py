"""DataFrame operators on sketches."""
