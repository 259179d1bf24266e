"""Spark-native near-duplicate removal for very large text corpora."""
