"""Compressed agglomerative clustering on Spark."""
