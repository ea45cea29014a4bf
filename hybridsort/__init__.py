"""A Spark-native adaptive radix and merge sorting engine."""
