"""Spark-native engine for semantic queries over media relations."""
