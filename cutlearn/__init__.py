"""cutlearn: learned, workload-aware cuts of a 2-D map for Spark, with the operators around them."""
