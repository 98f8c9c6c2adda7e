"""Spark-native ordering and traversal of large sparse graphs."""
