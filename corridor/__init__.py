"""corridor: error-bounded trajectory compression on Spark DataFrames."""
