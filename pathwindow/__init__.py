"""Shortest-path analytics on DataFrames: length windows that adapt to degrees and weights, and all around them."""
