"""Spark-native analytics for learning on graphs that keep changing."""
