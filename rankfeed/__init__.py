"""Spark-native engine for low-rank gradient compression with error feedback."""
