"""Filtered nearest-neighbour search over vectors in ordinary Parquet tables, on Spark."""
