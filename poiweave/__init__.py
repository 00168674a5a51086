"""Place discovery and region embedding on Spark DataFrames."""
