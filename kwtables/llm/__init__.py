"""Operators for training-data pipelines: extraction, tokenising, deduplication, filters, media and sharding.

Nothing outside this subpackage imports it; ``queries.py`` registers one query per operator.
"""
