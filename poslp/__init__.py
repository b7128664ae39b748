"""Spark-native engine for approximate positive linear programs on graphs."""
