"""Spark-native engine for discourse, incident and influence analytics."""
