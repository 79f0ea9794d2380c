"""Vertex programs executed as generalized sparse matrix-vector products on Spark DataFrames."""
