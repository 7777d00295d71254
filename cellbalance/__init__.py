"""cellbalance: contiguous, prefix-sum load balancing of cells and their particles on Spark DataFrames."""
