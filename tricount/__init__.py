"""Exact triangle counting on large networks with DataFrames."""
