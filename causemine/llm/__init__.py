"""Operators of a training-data pipeline.

Nothing else in the library imports this subpackage; it imports nothing from the rest either, so
it can be deleted without trace.
"""
