"""Matrices as DataFrames, their products, sketches, losses, baselines and measures."""
