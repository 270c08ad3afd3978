"""Spark-native alignment of two knowledge graphs by recursive fuzzy rules."""
