"""Spark-native curation of interleaved web corpora."""
