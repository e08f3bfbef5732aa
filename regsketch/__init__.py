"""Distinct counting with register sketches on Spark DataFrames, SQL and streams."""
