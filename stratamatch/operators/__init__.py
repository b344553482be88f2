"""Matching methods, estimators and measures over DataFrames."""
