"""Spark-native graph embedding engine."""
