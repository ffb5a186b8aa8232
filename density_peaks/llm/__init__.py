"""Operators of a training-data pipeline: dedup, quality, mixing, sharding, packing.

Nothing else in the package imports this subpackage.
"""
