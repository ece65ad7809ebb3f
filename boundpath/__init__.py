"""Spark-native constrained-path engine."""
