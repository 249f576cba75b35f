"""Sparse-tensor factorization on Spark."""
