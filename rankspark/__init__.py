"""Quantile summaries for very large data on Spark: build per partition, merge along a tree, answer any quantile."""
