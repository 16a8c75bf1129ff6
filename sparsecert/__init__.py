"""Sparse certificates of massive graphs, kept by groups of edges, on Spark."""
