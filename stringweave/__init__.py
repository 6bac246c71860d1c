"""stringweave: long-read assembly as sparse-matrix algebra on Spark DataFrames."""
