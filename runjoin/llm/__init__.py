"""Operators of a training-data pipeline: quality, dedup, tokenisation, scoring, archives, packing."""
