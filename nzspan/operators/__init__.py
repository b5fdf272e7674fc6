"""Matrices, layouts, vectors, products, baselines and solvers."""
