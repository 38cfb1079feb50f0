"""Operators of a training-data pipeline: deduplication, search, formatting, sharding, scoring, mixing.

Nothing else in the library imports this subpackage.
"""
