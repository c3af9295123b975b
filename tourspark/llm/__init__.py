"""Operators of a pipeline for training data. Nothing else in the library imports this."""
