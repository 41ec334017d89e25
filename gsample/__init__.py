"""gsample: graph sampling, graph metrics and streams of sampled edges on Spark DataFrames."""
