"""incstate: incremental state-vector simulation on Spark DataFrames."""
