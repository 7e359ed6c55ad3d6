"""edgefold: fused message passing on graphs, and the operators around it, as Spark DataFrames."""
