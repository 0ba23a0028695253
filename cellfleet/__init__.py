"""Spark-native spatial snapshot index and fleet-cost engine."""
