"""Geometric optimisation over join results that are never computed, on Spark DataFrames."""
