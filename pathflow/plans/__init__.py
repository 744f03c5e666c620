"""Walks as values: steps, binding, rewrites, lowering to DataFrames, text form."""
