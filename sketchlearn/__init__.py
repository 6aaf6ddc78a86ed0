"""Compact set hashing and linear learning on Spark DataFrames."""
