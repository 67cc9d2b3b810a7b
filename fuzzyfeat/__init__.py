"""Cluster-derived features for supervised detection, on Spark DataFrames."""
