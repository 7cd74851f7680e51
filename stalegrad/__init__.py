"""Spark-native engine for straggler-tolerant finite-sum optimisation."""
