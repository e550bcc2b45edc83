"""Operators on DataFrames: embedding, density, clustering, packing, baselines, measures."""
