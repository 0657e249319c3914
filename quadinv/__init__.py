"""Distributed dense matrix inversion on Spark DataFrames, with the cost model, baselines and workloads around it."""
