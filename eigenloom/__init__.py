"""eigenloom: spectral analytics for very large graphs on Spark DataFrames."""
