"""Spark-native entity linking between relational tuples and text mentions."""
