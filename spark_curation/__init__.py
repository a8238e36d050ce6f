"""Spark-native curation of crawled web pages with page programs."""
