"""Multi-vector retrieval on Spark: sets of vectors encoded as single vectors, searched, and re-scored exactly."""
