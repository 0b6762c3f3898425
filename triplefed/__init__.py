"""Adaptive pattern queries over federated triples, on Spark DataFrames."""
