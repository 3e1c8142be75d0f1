"""Spark-native byte-plane compression engine for fixed-width numeric columns."""
