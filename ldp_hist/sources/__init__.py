"""Populations (who holds what) and sinks."""
