"""Correlated high-utility pattern mining on Spark DataFrames."""
