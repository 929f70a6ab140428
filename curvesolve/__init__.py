"""Curve-ordered domain decomposition on Spark DataFrames."""
