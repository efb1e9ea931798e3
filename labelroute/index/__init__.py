"""Index structures: flat, inverted file, hyperplane buckets, proximity graphs."""
