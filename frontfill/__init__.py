"""frontfill: advancing-front domain filling and spatial thinning on Spark DataFrames."""
