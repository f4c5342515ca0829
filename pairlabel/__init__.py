"""Pair labeling without manual labels, and the operators around it, on Spark DataFrames."""
