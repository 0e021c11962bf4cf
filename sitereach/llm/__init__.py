"""Operators of a training-data pipeline. Optional: no other part of the library imports this package."""
