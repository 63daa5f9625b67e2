"""Windowing, clustering, assignment, projection, mask search, imputation and measures on DataFrames."""
