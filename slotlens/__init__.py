"""Spark-native cleansing of periodic series."""
