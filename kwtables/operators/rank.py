"""Importance of entities by damped iteration over the edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graph import KnowledgeGraph
from .lineage import store
from .row_ranks import Fold, Rounds

DAMPING, TOLERANCE = 0.85, 1e-8


def pagerank(graph: KnowledgeGraph, a: float = DAMPING, tol: float = TOLERANCE, tol_mode: str = "absolute", max_iter: int = 200, folded: Fold | None = None) -> DataFrame:
    """``node_id, pr``: starts at 1/V and stops when no rank moves by ``tol`` (times 1/V if relative).

    Mass of entities without edges is not handed on. Each round writes its ranks (two numbers for a
    node) and sends one number to the driver; edges carry their source's share, so a round is one join and one aggregate.

    ``folded`` (what ``row_ranks.fold`` says of the graph) runs ``max_iter`` rounds without a table of all nodes and edges and gives
    ``type_id, total, most, least`` of the ranks instead: sum, greatest and least, some types more than once.
    """
    if folded is not None:
        if tol > 0 or max_iter < 2:
            raise ValueError("a folded graph is ranked in a set number of rounds, two at least")
        return Rounds(graph, folded, a, max_iter).ranks()
    if tol_mode not in ("absolute", "relative"):
        raise ValueError(f"unknown tol_mode {tol_mode!r}")
    nodes = graph.nodes.select("node_id").distinct()
    n = nodes.count()
    if n == 0:
        return nodes.withColumn("pr", F.lit(0.0))
    out_degree = graph.edges.groupBy("src").agg(F.count(F.lit(1)).alias("degree"))
    edges = graph.edges.join(out_degree, "src").select("src", "dst", (F.lit(a) / F.col("degree")).alias("share"))
    edges, nodes = store(edges, by="src"), store(nodes, by="node_id")
    limit = tol / n if tol_mode == "relative" else tol
    ranks = nodes.withColumn("pr", F.lit(1.0 / n))
    base = (1.0 - a) / n
    for i in range(max_iter):
        given = edges.join(ranks, edges["src"] == ranks["node_id"]).groupBy("dst").agg(F.sum(F.col("pr") * F.col("share")).alias("given"))
        new = ranks.join(given, ranks["node_id"] == given["dst"], "left").select("node_id", (F.lit(base) + F.coalesce("given", F.lit(0.0))).alias("pr"), F.col("pr").alias("old"))
        new = store(new)
        moved = new.agg(F.max(F.abs(F.col("pr") - F.col("old")))).first()[0]
        ranks = new.select("node_id", "pr")
        if moved < limit:
            break
    return ranks
