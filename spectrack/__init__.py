"""Error-bounded trajectory compression on Spark DataFrames."""
