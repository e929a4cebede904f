"""Parallel parsing of delimiter-separated text on Spark."""
