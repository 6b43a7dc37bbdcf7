"""Spark-native selection of long training documents by far-reaching token dependencies."""

__version__ = "0.1.0"
