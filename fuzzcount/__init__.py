"""Spark-native private, typo-tolerant distinct counting."""
