"""Spark-native engine for graph-pattern and other multiway join queries."""
