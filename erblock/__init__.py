"""Spark-native blocking for entity resolution and its evaluation."""
