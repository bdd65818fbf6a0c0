"""Spark-native analytics on very large directed property graphs."""
