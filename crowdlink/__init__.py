"""Spark-native entity resolution with fallible voters."""
