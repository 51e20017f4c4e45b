"""treesieve: pruning-tree analytics on Spark DataFrames."""
