"""Operators of a training-data pipeline: sharding, packing, filters, search, deduplication.

Nothing else in the library imports this subpackage.
"""
