"""Operators on training corpora: scoring, deduplication, search, mixing, packing."""
