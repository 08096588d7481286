"""Influence maximisation on undirected graphs, built on Spark DataFrames."""
