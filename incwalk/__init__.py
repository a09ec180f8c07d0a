"""Spark-native engine for random-walk ranking on graphs that change."""

__version__ = "0.1.0"
