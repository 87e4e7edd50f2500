"""Operators for preparing training text: search, filtering, deduplication, packing."""
