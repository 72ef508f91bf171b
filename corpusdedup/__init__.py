"""Spark-native sub-document deduplication with frequency- and length-aware copy budgets."""

__version__ = "0.1.0"
