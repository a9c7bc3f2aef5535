"""Spark-native contact fan-out analytics."""
