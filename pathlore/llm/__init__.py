"""Operators of a large-scale training-data pipeline.

Nothing else in the library imports this subpackage. Each module holds one
operator with its own general interface; ``registry`` holds the thin queries
that apply the operators to the given tables.
"""
