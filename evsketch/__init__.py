"""Approximate distinct counting with extreme-value sketches on Spark DataFrames."""
