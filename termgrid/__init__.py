"""Keyword search over joined tables by the terms that co-occur most, for Spark."""
