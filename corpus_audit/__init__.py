"""Spark-native audit engine for large text corpora."""
