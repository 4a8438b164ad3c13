"""Spark-native conflation of overlapping point-of-interest sources."""
