"""Keyword queries answered by ranked tables over a typed knowledge graph, on Spark."""
