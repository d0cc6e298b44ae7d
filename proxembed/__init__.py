"""Vertex embeddings of large partitioned graphs, learned with Spark DataFrames and Arrow kernels."""
