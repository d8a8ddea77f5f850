"""Operators of a training-data pipeline, beside the placement engine and imported by nothing else in it."""
