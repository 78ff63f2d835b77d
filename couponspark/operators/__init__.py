"""Operators on DataFrames: sketch state, estimators, merges, codecs."""
