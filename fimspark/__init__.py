"""Spark-native frequent-itemset mining under a memory budget."""

__version__ = "0.1.0"
