"""sparsepairs: join-project size estimation, written for Spark DataFrames."""
