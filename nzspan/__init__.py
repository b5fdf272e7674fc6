"""Sparse products on Spark: even splits of stored entries, shared columns, solvers."""
