"""Operators of a training-data pipeline: tokenising, deduplication, filtering, sharding, scoring."""
