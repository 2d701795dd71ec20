"""Spark-native analytics for open quantum dynamics."""
