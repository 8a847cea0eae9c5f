"""Pattern counting and mining on Spark: decomposition of patterns into overlapping parts."""
