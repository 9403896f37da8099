"""Spark-native engine for judging compressed text embeddings."""
