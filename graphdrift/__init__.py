"""Adaptive partitioning of changing graphs on Spark."""
