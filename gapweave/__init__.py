"""Spark-native engine for filling gaps in large collections of fixed-interval time series."""
