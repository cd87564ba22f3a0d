"""Spark-native hybrid recommendation engine: content-coupled factorization, fusion and evaluation."""
