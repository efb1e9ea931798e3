"""Label-constrained vector search on Spark, driven by index selection."""
