"""Spark-native near-duplicate detection: signatures, terms, search, scoring, clustering."""
