"""modspark: streaming graph clustering by modularity on Spark DataFrames."""
