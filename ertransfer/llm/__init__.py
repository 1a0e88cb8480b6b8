"""Operators of a training-data pipeline: dedup, filters, scoring, search, mixing and sharding."""
