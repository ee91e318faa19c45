"""Spark-native hybrid graph and relational analytics engine."""
