"""Timed-episode mining on Spark: counting, culling and mining serial episodes in event streams."""
