"""Yield maps from hand-harvest cart traces, on Spark DataFrames."""
