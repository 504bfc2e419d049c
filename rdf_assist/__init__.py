"""Query assistance over graph-shaped data, written for Spark DataFrames."""
