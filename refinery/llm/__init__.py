"""Operators of a large-scale training-data pipeline, and their registered queries.

Nothing outside this subpackage imports it.
"""
