"""Spark-native engine that gives network-embedding algorithms a good start."""
