"""Importance without a table of all nodes and edges: rounds over few nodes, ranks of rows from their owners' past.

A graph's rows (nodes keyed by row, as line items) are entered from one owner only (their order), so all rows of an owner
have one rank, and an owner is entered from its rows and from one other node (its customer). Owner and rows thus follow in every
round from the ranks that this node had before. Written are one table of rows and owners, dealt by that node, and in each
round the ranks of the nodes that are left (customers, suppliers, nations, regions). Nodes that lead to literals alone (parts)
and literals hand nothing on and are ranked in the last round.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graph import EdgePart, KnowledgeGraph, no_key_twice
from .lineage import dealt, drop_dealt, shuffles_dropped, store


@dataclass(frozen=True)
class Fold:
    """Places of the parts: rows, their owner, nodes that are ranked in each round, nodes that are ranked in the last; and the
    edges from the owner to its rows and from the node before the owner."""

    rows: int
    owner: int
    kept: tuple[int, ...]
    late: tuple[int, ...]
    down: EdgePart
    before: EdgePart


def fold(graph: KnowledgeGraph) -> Fold | None:
    """How the graph's schema folds; None if it does not, or if a key is there twice."""
    if graph.parts is None or graph.ranks is not None:
        return None
    nodes, edges = graph.parts
    literal = [p.source[1] == "literal" for p in nodes]
    rows = [i for i, p in enumerate(nodes) if p.plain is not None and not literal[i]]
    if len(rows) != 1:
        return None
    r = rows[0]
    down = [e for e in edges if e.dst == r]
    if len(down) != 1 or down[0].plain_end is None:
        return None
    b = down[0].src
    into = [e for e in edges if e.dst == b]
    up, before = [e for e in into if e.src == r], [e for e in into if e.src != r]
    own = lambda e, end: (e.src_source if end == "src" else e.dst_source) == nodes[b].source
    if len(before) != 1 or not own(before[0], "dst") or before[0].src == b or any(e.dst_source != down[0].src_source for e in up):
        return None
    if nodes[b].table is None or any(not own(e, "src") for e in edges if e.src == b and e.dst != r):
        return None
    rest = [i for i in range(len(nodes)) if i not in (r, b) and not literal[i]]
    late = tuple(i for i in rest if all(literal[e.dst] for e in edges if e.src == i) and all(e.src == r for e in edges if e.dst == i))
    if any(nodes[i].table is None or not no_key_twice(nodes[i].keys) for i in (*rest, b)):
        return None
    return Fold(r, b, tuple(i for i in rest if i not in late), late, down[0], before[0])


def _sum(columns: list[Column]) -> Column:
    return reduce(Column.__add__, columns, F.lit(0))


def _there(column: Column) -> Column:
    return column.isNotNull().cast("int")


class Rounds:
    """Ranks of the folded graph after ``rounds`` rounds (two at least)."""

    def __init__(self, graph: KnowledgeGraph, at: Fold, a: float, rounds: int) -> None:
        self.graph, self.at, self.a, self.rounds = graph, at, a, rounds
        self.nodes, self.edges = graph.parts
        self.spark = graph.types.sparkSession
        self.literal = {i for i, p in enumerate(self.nodes) if p.source[1] == "literal"}
        self.n = sum((p.rows if p.plain is None else p.plain).count() for p in self.nodes)
        self.base, self.start = (1.0 - a) / max(self.n, 1), 1.0 / max(self.n, 1)
        self.places = max(int(self.spark.conf.get("spark.sql.shuffle.partitions")), 1)
        entity = [e for e in self.edges if e.dst not in self.literal]
        self.row_ends = [e for e in entity if e.src == at.rows and e.dst != at.owner]
        self.owner_ends = [e for e in entity if e.src == at.owner and e.dst != at.rows]

    def literals(self, part: int) -> list[EdgePart]:
        return [e for e in self.edges if e.src == part and e.dst in self.literal]

    def members(self) -> DataFrame:
        """A row for each row node and each owner without rows: ``c`` (the node before the owner), ``held`` (whether the owner is a node),
        ``first`` (one row of each owner), ``degree``, ``back`` (what the owner gets of its rows' rank), ``line``, ``w`` (what an edge
        of the row gets of its rank), numbers of literals, the rows' ends ``r<k>`` and the owner's ``o<k>``."""
        at, p = self.at, self.nodes[self.at.rows]
        ends = [e.plain_end.alias(f"r{k}") for k, e in enumerate(self.row_ends)]
        texts = _sum([_there(e.plain_end) for e in self.literals(at.rows)])
        ups = [e for e in self.edges if e.src == at.rows and e.dst == at.owner]
        lines = p.plain.select(at.down.plain_end.alias("owner"), texts.alias("texts"), *ends)
        out = _sum([F.col("texts"), *(_there(F.col(f"r{k}")) for k in range(len(ends)))]) + len(ups)
        lines = lines.withColumn("w", F.lit(self.a) / out)
        whole = Window.partitionBy("owner")
        lines = lines.select("*", F.sum("w").over(whole).alias("sum_w"), F.count(F.lit(1)).over(whole).alias("rows"), F.row_number().over(whole.orderBy("owner")).alias("at"))
        b = self.nodes[at.owner]
        own = [e.dst_ident.alias(f"o{k}") for k, e in enumerate(self.owner_ends)]
        owners = b.table.select(b.ident.alias("id"), at.before.src_ident.alias("c"), _sum([_there(e.dst_ident) for e in self.literals(at.owner)]).alias("owner_texts"), *own)
        both = lines.join(owners, lines["owner"] == owners["id"], "full")
        held, line = F.col("id").isNotNull(), F.col("owner").isNotNull()
        degree = F.coalesce("rows", F.lit(0)) + F.col("owner_texts") + _sum([_there(F.col(f"o{k}")) for k in range(len(own))])
        first = held & (~line | (F.col("at") == 1))
        back = F.coalesce("sum_w", F.lit(0.0)) * len(ups)
        return both.select("c", held.alias("held"), first.alias("first"), F.when(held & (degree > 0), degree).cast("double").alias("degree"), back.alias("back"), line.alias("line"), "w", "texts", "owner_texts", *(f"r{k}" for k in range(len(ends))), *(F.when(first, F.col(f"o{k}")).alias(f"o{k}") for k in range(len(own))))

    def owner_rank(self, t: int) -> Column:
        """From the shares ``s0..`` of the node before the owner, null if there is none."""
        if t == 0:
            return F.lit(self.start)
        return F.lit(self.base) + F.lit(self.a) * F.coalesce(f"s{t - 1}", F.lit(0.0)) + F.col("back") * self.row_rank(t - 1)

    def row_rank(self, t: int) -> Column:
        if t == 0:
            return F.lit(self.start)
        return F.lit(self.base) + F.when(F.col("held"), F.lit(self.a) / F.col("degree") * self.owner_rank(t - 1)).otherwise(0.0)

    def past(self, ranked: DataFrame, t: int) -> DataFrame:
        """Rows and owners with the shares of rounds 0..t-1 of the node before."""
        shares = ranked.select("id", *((F.col(f"p{k}") / F.col("degree")).alias(f"s{k}") for k in range(t)))
        return self.table.join(shares.hint("shuffle_hash"), self.table["c"] == shares["id"], "left").drop("id")

    def given(self, ranked: DataFrame, t: int) -> DataFrame:
        """``dst, given`` of round ``t``: what rows and owners hand on of round t-1, added up."""
        rows = [F.struct(F.col(f"r{k}").alias("dst"), (F.col("w") * F.col("x")).alias("given")) for k, e in enumerate(self.row_ends) if e.dst in self.at.kept]
        owners = [F.struct(F.col(f"o{k}").alias("dst"), (F.lit(self.a) / F.col("degree") * F.col("y")).alias("given")) for k, _ in enumerate(self.owner_ends)]
        known = self.past(ranked, t).withColumns({"x": self.row_rank(t - 1), "y": self.owner_rank(t - 1)})
        return known.select(F.explode(F.array(*rows, *owners)).alias("e")).select("e.*").where("dst IS NOT NULL").groupBy("dst").agg(F.sum("given").alias("given"))

    def degrees(self, parts: tuple[int, ...]) -> DataFrame:
        """``id, part, degree`` (null without edges) of the parts' nodes."""
        rows = reduce(DataFrame.unionByName, [self.nodes[i].rows.select(F.col("node_id").alias("id"), F.lit(i).alias("part")) for i in parts])
        out = [e.rows.select("src") for e in self.edges if e.src in parts]
        if not out:
            return rows.withColumn("degree", F.lit(None).cast("double"))
        per = reduce(DataFrame.unionByName, out).groupBy("src").agg(F.count(F.lit(1)).cast("double").alias("degree"))
        return rows.join(per, rows["id"] == per["src"], "left").drop("src")

    def ranks(self) -> DataFrame:
        """``type_id, total, most, least``: sum, greatest and least rank of the nodes of each type, some types more than once."""
        name = f"ranks_{uuid.uuid4().hex}"
        with shuffles_dropped(self.spark):
            self.table = dealt(self.members(), "c", self.places, f"{name}_members")
            ranked = dealt(self.degrees(self.at.kept).withColumn("p0", F.lit(self.start)), "id", self.places, f"{name}_0")
            links = [e.rows for e in self.edges if e.src in self.at.kept and e.dst in self.at.kept]
            links = store(reduce(DataFrame.unionByName, links)) if links else None
            for t in range(1, self.rounds + 1):
                parts = [self.given(ranked, t)]
                if links is not None:
                    handed = ranked.select("id", (F.lit(self.a) * F.col(f"p{t - 1}") / F.col("degree")).alias("given"))
                    parts.append(links.join(handed, links["src"] == handed["id"]).select("dst", "given"))
                sums = reduce(DataFrame.unionByName, parts).groupBy("dst").agg(F.sum("given").alias("given"))
                new = ranked.join(sums, ranked["id"] == sums["dst"], "left")
                ranked = dealt(new.select(ranked["*"], (F.lit(self.base) + F.coalesce("given", F.lit(0.0))).alias(f"p{t}")), "id", self.places, f"{name}_{t}")
                drop_dealt(self.spark, f"{name}_{t - 1}")
            out = store(self._last(ranked))
            for made in (f"{name}_{self.rounds}", f"{name}_members"):
                drop_dealt(self.spark, made)
            return out

    def _last(self, ranked: DataFrame) -> DataFrame:
        end, type_of = self.rounds, {i: p.type_id for i, p in enumerate(self.nodes)}
        known = self.past(ranked, end).withColumns({"x": self.row_rank(end), "y": self.owner_rank(end), "x1": self.row_rank(end - 1), "y1": self.owner_rank(end - 1)})
        text = type_of[min(self.literal)] if self.literal else 0

        def summed(df: DataFrame, of: list[tuple[int, Column, Column]]) -> list[DataFrame]:
            """Of (type, rank, number of nodes with it; null or 0 where there is none)."""
            sums = []
            for k, (_, pr, n) in enumerate(of):
                own = F.when(n > 0, pr)
                sums += [F.sum(own * n).alias(f"total{k}"), F.max(own).alias(f"most{k}"), F.min(own).alias(f"least{k}")]
            row = store(df.agg(*sums))
            return [row.select(F.lit(kind).alias("type_id"), F.col(f"total{k}").alias("total"), F.col(f"most{k}").alias("most"), F.col(f"least{k}").alias("least")) for k, (kind, _, _) in enumerate(of)]

        base, a = F.lit(self.base), F.lit(self.a)
        line, first = F.col("line").cast("int"), F.col("first").cast("int")
        out = summed(known, [(type_of[self.at.rows], F.col("x"), line), (type_of[self.at.owner], F.col("y"), first), (text, base + F.col("w") * F.col("x1"), F.when(F.col("line"), F.col("texts"))), (text, base + a / F.col("degree") * F.col("y1"), F.when(F.col("first"), F.col("owner_texts")))])
        for i in (*self.at.kept, *self.at.late):
            if i in self.at.late:
                ends = [(F.col(f"r{k}"), F.col("w")) for k, e in enumerate(self.row_ends) if e.dst == i]
                late = self.past(ranked, end - 1).withColumns({"x1": self.row_rank(end - 1), "x2": self.row_rank(end - 2)})
                sums = reduce(DataFrame.unionByName, [late.select(d.alias("dst"), (w * F.col("x1")).alias("g"), (w * F.col("x2")).alias("g1")).where("dst IS NOT NULL") for d, w in ends]).groupBy("dst").agg(F.sum("g").alias("g"), F.sum("g1").alias("g1"))
                own = self.degrees((i,))
                own = own.join(sums, own["id"] == sums["dst"], "left").select("id", "degree", (base + F.coalesce("g", F.lit(0.0))).alias("now"), (base + F.coalesce("g1", F.lit(0.0))).alias("was"))
            else:
                own = ranked.where(F.col("part") == i).select("id", "degree", F.col(f"p{end}").alias("now"), F.col(f"p{end - 1}").alias("was"))
            held = self.literals(i)
            if held:
                per = reduce(DataFrame.unionByName, [e.rows.select("src") for e in held]).groupBy("src").agg(F.count(F.lit(1)).alias("texts"))
                own = own.join(per, own["id"] == per["src"], "left")
            out += summed(own, [(type_of[i], F.col("now"), F.lit(1))] + ([(text, base + a / F.col("degree") * F.col("was"), F.col("texts"))] if held else []))
        return reduce(DataFrame.unionByName, out).where("most IS NOT NULL")
