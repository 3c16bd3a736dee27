"""Operators of a training-data pipeline: scanning, formatting, tokenising, deduplicating, packing.

Nothing outside this folder imports it.  ``registry`` lists its queries and their SQL.
"""
