"""Operators of a training-data pipeline: counting, cleaning, de-duplicating, scoring and packing documents.

Nothing outside this folder imports it.
"""
