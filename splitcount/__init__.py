"""Compressed, mergeable distinct-count sketches on Spark DataFrames."""
