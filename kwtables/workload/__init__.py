"""Fixtures, query sets and experiments."""
