"""Bit-optimal dictionary parsing on Spark."""
