"""Nearest- and farthest-vector analytics on Spark."""
