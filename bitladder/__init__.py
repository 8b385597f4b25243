"""Progressive binary codes for exhaustive retrieval, on Spark DataFrames."""
