"""Graph queries as recursive rules, on Spark DataFrames."""
