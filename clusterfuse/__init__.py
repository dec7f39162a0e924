"""Spark-native engine for Gaussian cluster overlap measures and cluster fusion."""
