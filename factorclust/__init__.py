"""K-means through a nonnegative low-rank factor, on Spark DataFrames."""
