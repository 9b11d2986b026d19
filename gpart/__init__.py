"""Balanced graph partitioning at very large scale, on DataFrames, Spark SQL and Structured Streaming."""
