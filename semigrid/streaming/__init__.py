"""Incremental matrices from event streams."""
