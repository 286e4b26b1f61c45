"""Spark-native, updatable navigable-graph vector index and relational companion operators."""
