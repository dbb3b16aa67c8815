"""Spark-native, knowledge-graph-grounded event extraction."""
