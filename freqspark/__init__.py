"""Frequent items over Spark DataFrames: bounded counter summaries, their merges, verification and measures."""
