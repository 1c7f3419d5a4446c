"""Influence and passage retrieval over large corpora, on Spark DataFrames."""
