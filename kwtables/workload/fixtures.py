"""Small graphs with known answers."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..functions.text import tokenize
from ..operators.search import Query
from ..sources.graph import KnowledgeGraph, schema_table


def small_graph(spark: SparkSession, nodes: list[tuple[int, str, str]], edges: list[tuple[int, str, int]], literals: set[int] | None = None) -> KnowledgeGraph:
    """Graph of (id, type, text) nodes and (src, attr, dst) edges; ids in ``literals`` are plain text."""
    literals = literals or set()
    types = ["Text", *sorted({t for i, t, _ in nodes if i not in literals and t != "Text"})]
    attrs = sorted({a for _, a, _ in edges}) or ["none"]
    rows = [(i, f"{t}/{i}", 0 if i in literals else types.index(t), text, i in literals) for i, t, text in nodes]
    table = spark.createDataFrame(rows, "node_id bigint, node_key string, type_id int, text string, is_literal boolean")
    arcs = spark.createDataFrame([(s, attrs.index(a), d) for s, a, d in edges], "src bigint, attr_id int, dst bigint")
    return KnowledgeGraph(table.select("node_id", "node_key", "type_id", "text", tokenize(F.col("text")).alias("tokens"), "is_literal"), arcs, schema_table(spark, types, "type"), schema_table(spark, attrs, "attr"))


def software(spark: SparkSession) -> tuple[KnowledgeGraph, Query]:
    """Software, models, companies and a book; four words, nine patterns, ten subtrees."""
    nodes = [(1, "Software", "alpha engine"), (2, "Model", "relational database"), (3, "Company", "acme"), (4, "Text", "us 77 billion"), (7, "Software", "beta engine"), (8, "Company", "bolt corp"), (9, "Model", "document database"), (10, "Text", "us 37 billion"), (12, "Book", "guide to database software in practice"), (13, "Company", "paper press"), (14, "Text", "us 9 billion")]
    edges = [(1, "genre", 2), (1, "developer", 3), (3, "revenue", 4), (7, "genre", 9), (7, "developer", 8), (8, "revenue", 10), (1, "reference", 12), (12, "publisher", 13), (13, "revenue", 14)]
    return small_graph(spark, nodes, edges, {4, 10, 14}), Query(("database", "software", "company", "revenue"))


def all_empty(spark: SparkSession, p: int) -> tuple[KnowledgeGraph, Query]:
    """Two roots of one type, each with p leaves of its own types that hold one of two words: no pattern has a subtree."""
    nodes = [(1, "Top", "first"), (2, "Top", "second")]
    edges = []
    for i in range(p):
        nodes += [(10 + i, f"Left{i}", "red"), (1000 + i, f"Right{i}", "blue")]
        edges += [(1, f"left{i}", 10 + i), (2, f"right{i}", 1000 + i)]
    return small_graph(spark, nodes, edges), Query(("red", "blue"))


def hub(spark: SparkSession, leaves: int) -> tuple[KnowledgeGraph, Query]:
    """One root with many leaves that hold both words."""
    nodes = [(0, "Hub", "centre"), *((i, "Leaf", "red blue") for i in range(1, leaves + 1))]
    return small_graph(spark, nodes, [(0, "has", i) for i in range(1, leaves + 1)]), Query(("red", "blue"), validity="product")
