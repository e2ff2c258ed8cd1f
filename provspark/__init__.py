"""Spark-native provenance and quality engine for training collections."""
