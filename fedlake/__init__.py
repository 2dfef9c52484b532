"""Federated recommendation over client-partitioned data, on Spark DataFrames."""
