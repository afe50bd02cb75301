"""vecspark: clustering of embedding vectors and inverted-file indexes on Spark DataFrames."""
