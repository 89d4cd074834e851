"""Operators for training-data pipelines: quality, deduplication, mixing, extraction, tokens, packing, archives, personal data."""
