"""Spark-native estimation of hidden-state networks of nodes and links."""
