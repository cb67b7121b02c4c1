"""Spark-native discovery of every minimal key of a table."""
