"""Paths, path patterns and tree patterns as array expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def path_pattern(labels: Column, ends_on_edge: bool) -> Column:
    """Label array of a match: types and attributes in turn; a match on the last edge leaves out the last type."""
    return F.slice(labels, F.lit(1), F.size(labels) - 1) if ends_on_edge else labels


def path_length(labels: Column) -> Column:
    """Number of nodes, counting the end node of a matched edge."""
    return F.floor(F.size(labels) / 2).cast("int") + 1


def tree_pattern(ids: list[str]) -> Column:
    """Vector of path-pattern ids, one for each word in query order; equal vectors are equal patterns."""
    return F.array(*ids)


def height(lengths: list[Column]) -> Column:
    return F.greatest(*lengths) if len(lengths) > 1 else lengths[0]


def edges_of(nodes: Column, attrs: Column) -> Column:
    """Edges of one path as (src, attr, dst) structs."""
    return F.transform(attrs, lambda a, i: F.struct(F.get(nodes, i).alias("src"), a.alias("attr"), F.get(nodes, i + 1).alias("dst")))


def is_tree(edge_sets: list[Column]) -> Column:
    """Whether paths from one root form a tree: no node is entered by two different edges.

    Paths are simple and start at the root, so the root is never entered, and distinct edges equal entered nodes
    exactly if every other node of the union has one edge into it.
    """
    edges = F.array_distinct(F.flatten(F.array(*edge_sets)))
    return F.size(edges) == F.size(F.array_distinct(F.transform(edges, lambda e: e["dst"])))


def is_minimal(edge_sets: list[Column], ends: list[Column]) -> Column:
    """Whether every leaf of the union of the edges is where some word's path ends; true for any union of such paths."""
    edges = F.array_distinct(F.flatten(F.array(*edge_sets)))
    leaves = F.array_except(F.transform(edges, lambda e: e["dst"]), F.transform(edges, lambda e: e["src"]))
    return F.size(F.array_except(leaves, F.array(*ends))) == 0


def root_sample(root: Column, seed: int, rate: Column) -> Column:
    """Bernoulli choice by a digest of the root: the same roots in any engine and any partitioning."""
    digest = F.conv(F.substring(F.md5(F.concat_ws("|", root.cast("string"), F.lit(str(seed))).cast("binary")), 1, 8), 16, 10).cast("double")
    return digest / F.lit(4294967296.0) < rate
