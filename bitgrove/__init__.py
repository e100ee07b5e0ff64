"""Spark-native sampling and reconstruction of sets kept as Bloom filters."""
