"""Operators of a training-data pipeline: mixing, deduplication, filtering, tokenizing, sharding and archives.

Nothing else in the library imports this subpackage.
"""
