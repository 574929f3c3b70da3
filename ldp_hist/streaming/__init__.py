"""Counters over streams."""
