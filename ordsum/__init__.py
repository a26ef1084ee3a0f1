"""Ordered maps with monoid summaries, on Spark DataFrames."""
