"""Operators on point tables; every one takes and returns DataFrames."""
