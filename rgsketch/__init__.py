"""Weighted minwise sketching for Spark DataFrames."""
