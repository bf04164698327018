"""Keyword trends over event streams, and appending to a stored index."""
