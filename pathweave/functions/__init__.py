"""Functions over paths."""
