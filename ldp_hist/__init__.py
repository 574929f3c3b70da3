"""Locally private frequency estimation and heavy hitters on Spark."""
