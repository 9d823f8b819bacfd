"""Operators from DataFrames to DataFrames: search, graphs, quantization models, measures."""
