"""Exact Euclidean similarity search with ball trees, as Spark relations."""
