"""Spark-native linear sketches for very large dynamic graphs."""
