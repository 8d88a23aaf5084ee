"""Spark-native deterministic matrix sketching."""
