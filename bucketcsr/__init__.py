"""Spark-native static hash indexes laid out as compressed sparse rows."""
