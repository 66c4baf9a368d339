"""Spark-native synthesis of two-column mapping relationships."""
