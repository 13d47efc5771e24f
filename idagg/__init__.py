"""Spark-native engine for identity-aware aggregation over very large record streams."""
