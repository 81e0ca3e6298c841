"""Operators of a training-data pipeline, each usable on its own DataFrame.

Nothing else in the library imports this subpackage.
"""
