"""Operators of a training-data pipeline: extraction, filtering, deduplication, mixing.

Nothing outside this subpackage imports it; ``registry`` lists its queries and their SQL.
"""
