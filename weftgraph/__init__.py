"""Subgraph pattern matching and counting on Spark DataFrames."""
