"""Reliable column relationships on Spark."""
