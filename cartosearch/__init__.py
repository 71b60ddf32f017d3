"""Two-granularity search over repositories of point datasets, on Spark DataFrames."""
