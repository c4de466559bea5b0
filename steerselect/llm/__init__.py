"""Operators of a training-data pipeline: deduplication, search, privacy, archives, packing, encoding, placement.

Nothing outside this subpackage imports it.
"""
