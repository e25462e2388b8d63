"""Sparse multi-way arrays on Spark: building, factorisation, prediction and measures."""
