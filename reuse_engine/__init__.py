"""Spark-native analytics of code reuse over very large program collections."""
