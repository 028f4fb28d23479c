"""Spark-native curation, change tracking and querying of bibliographic records."""
