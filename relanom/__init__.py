"""Spark-native anomaly ranking over multi-table relational data."""
