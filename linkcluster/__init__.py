"""Multi-source entity clustering on Spark DataFrames."""
