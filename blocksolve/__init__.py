"""Spark-native row-and-column block solver for huge sparse linear systems."""
