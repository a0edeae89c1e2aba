"""The search methods."""
