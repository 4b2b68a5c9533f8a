"""Overlapping domain-decomposition solvers for large sparse systems, built on Spark DataFrames."""
