"""Spark-native mining of knowledge graphs from incident reports."""
