"""Spark-native engine for analysis-scoped variable metadata.

The package keeps its import light: executors import it by reference when a
Python operator runs, so nothing here starts Spark or loads a model.
"""
