"""Vertex programs with remote field access, on Spark DataFrames."""
