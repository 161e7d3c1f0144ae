"""Operators of a training-data pipeline: counting, filtering, deduplication, scoring and packing."""
