"""Operators of a training-data pipeline: text scoring, tokenising, packing, similarity joins and vector search."""
