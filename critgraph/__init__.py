"""critgraph: critical-path performance modelling on Spark DataFrames."""
