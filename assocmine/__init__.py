"""Spark-native discovery of significant associations among discrete attributes."""

__version__ = "0.1.0"
