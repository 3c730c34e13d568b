"""Spark-native enumeration of minimal connecting subgraphs."""
