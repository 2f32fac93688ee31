"""Operators of a training-data pipeline over very large document tables.

Nothing outside this subpackage imports it.
"""
