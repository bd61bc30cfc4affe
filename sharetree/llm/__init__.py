"""Operators of a training-data pipeline: sharding, mixing, deduplication, filtering, formatting and storage of text."""
