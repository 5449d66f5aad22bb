"""Connected components and single-linkage clustering of very large graphs on Spark DataFrames."""
