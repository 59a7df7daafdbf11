"""Full-neighbourhood message aggregation and graph-network training on Spark DataFrames."""
