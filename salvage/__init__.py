"""Spark-native engine that turns low-rated instruction data into usable data."""
