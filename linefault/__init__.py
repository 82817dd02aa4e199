"""Spark-native fault detection and fault typing from device telemetry and customer tickets."""
