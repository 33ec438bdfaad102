"""Spark-native inter-frame computation reuse for per-frame token encoders."""
