"""Operators of a training-data pipeline: dedup, scans, quality, packing, search, mixing and sharding.

Nothing else in the library imports this subpackage; its queries are in :mod:`distds.llm.queries`.
"""
