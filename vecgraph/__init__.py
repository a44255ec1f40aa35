"""Proximity-graph search over compact vector codes, on Spark DataFrames."""
