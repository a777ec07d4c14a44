"""Operators of a training-data pipeline, with their queries and SQL.

Nothing else in the library imports this subpackage.
"""
