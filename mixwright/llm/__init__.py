"""Operators of a training-data pipeline: sharding, scoring, filtering, dedup, packing and output formats.

Nothing outside this subpackage imports it.
"""
