"""State-vector simulation over chunked, distributed registers on Spark DataFrames."""
