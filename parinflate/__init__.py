"""Spark-native engine over gzip-compressed data: find, decode, link, index and query."""
