"""Spark-native engine for privacy-preserving record linkage with layered review."""
