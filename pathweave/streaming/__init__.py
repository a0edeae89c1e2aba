"""Graphs from streams."""
