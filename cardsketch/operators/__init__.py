"""Sketch builders, estimators and measures over DataFrames."""
