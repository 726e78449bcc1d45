"""Operators for training-data pipelines, each usable on its own DataFrame.

Nothing else in the library imports this subpackage.
"""
