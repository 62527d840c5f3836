"""Spark-native singular value decomposition of tables."""
