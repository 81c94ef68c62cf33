"""Link-based importance ranks of changing directed graphs, on Spark DataFrames."""
