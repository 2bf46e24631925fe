"""Learned scheduling of batches of concurrent queries, on Spark."""
