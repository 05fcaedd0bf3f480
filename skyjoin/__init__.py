"""Probabilistic cross-matching of sky catalogs on Spark DataFrames."""
