"""Matching engine for observational causal analysis on Spark DataFrames."""
