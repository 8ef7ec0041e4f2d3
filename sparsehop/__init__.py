"""Masked sparse matrix-vector graph analytics on Spark DataFrames."""
