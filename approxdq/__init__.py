"""Approximate data quality metrics over triples, Spark-native."""
