"""Compressed-vector analytics on Spark."""
