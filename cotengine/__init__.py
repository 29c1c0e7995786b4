"""Spark-native engine for curating reasoning data and for failure-driven resampling."""
