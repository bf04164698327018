"""Importance ranks, the path index and the search methods."""
