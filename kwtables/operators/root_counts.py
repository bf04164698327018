"""Numbers of paths from each root to each word, without forming a path: what a root has within two edges is added up.

For up to three nodes, a root's paths are those of its neighbours with up to two nodes, less the ways back to the root. An edge
rule names its neighbours either in the root's own row (``up``: one at most) or in the rows of the neighbours (``down``: grouped by
the key that they name). Nodes keyed by row are rows without their made keys.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.graph import no_key_twice
from .lineage import shuffles_dropped, store
from .walk import ROOT_ROWS, TAIL_ROWS, Walk, WalkedIndex, few


def path_counts(index: WalkedIndex, words: list[str]) -> DataFrame | None:
    """``root_type, n0.., m``: the number of roots (m) with so many paths to each word, of all roots that reach one. None if the
    schema has other edges than these, a key is there twice, or paths may have other than three nodes."""
    if index.d != 3 or any(w.isdigit() for w in words):
        return None
    walk = Walk(index, words, True)
    counts = RootCounts(walk)
    if not counts.countable():
        return None
    with shuffles_dropped(index.graph.types.sparkSession):
        return counts.table()


class RootCounts:
    def __init__(self, walk: Walk) -> None:
        self.walk, self.words, self.nodes, self.edges = walk, walk.words, walk.nodes, walk.edges
        self.literal = {i for i, p in enumerate(self.nodes) if p.source[1] == "literal"}
        self.rows = [i for i, p in enumerate(self.nodes) if p.plain is not None and i not in self.literal]
        self.places = range(len(self.words))

    # -- the schema

    def up(self, part: int) -> list[int]:
        """Edges whose end is named in the part's own rows."""
        return [k for k, e in enumerate(self.edges) if e.src == part and e.dst not in self.literal and e.src_source == self.nodes[part].source]

    def down(self, part: int) -> list[int]:
        """Edges to nodes whose own rows name the part."""
        return [k for k, e in enumerate(self.edges) if e.src == part and e.dst not in self.literal and e.src_source != self.nodes[part].source and e.dst_source == self.nodes[e.dst].source]

    def back(self, k: int) -> list[int]:
        return [j for j, f in enumerate(self.edges) if f.src == self.edges[k].dst and f.dst == self.edges[k].src]

    def countable(self) -> bool:
        entity = [k for k, e in enumerate(self.edges) if e.dst not in self.literal]
        for k in entity:
            e = self.edges[k]
            if e.src == e.dst or k not in self.up(e.src) + self.down(e.src):
                return False
            back = self.back(k)
            if len(back) > 1 or any((self.edges[j].src_source, self.edges[j].dst_source) != (e.dst_source, e.src_source) for j in back):
                return False
        if any(self.edges[k].plain_end is None for k in entity if {self.edges[k].src, self.edges[k].dst} & set(self.rows)):
            return False
        if any(not self.nodes[i].digits or len([k for k in entity if self.edges[k].dst == i]) > 1 or any(self.back(k) and self.edges[k].dst != self.edges[self.back(k)[0]].src for k in self.up(i)) for i in self.rows):
            return False
        plain = [i for i in range(len(self.nodes)) if i not in self.literal and i not in self.rows]
        return all(self.nodes[i].table is not None and no_key_twice(self.nodes[i].keys) for i in plain)

    # -- hits

    def attr(self, k: int, w: int) -> int:
        return int((self.words[w], self.edges[k].attr_id) in self.walk.sims["attr"])

    def by_text(self, part: int) -> list[int]:
        """Words that some of the part's nodes hold and others do not."""
        return [w for w in self.places if (self.words[w], part) in self.walk.in_text and not self.by_type(part, w)]

    def by_type(self, part: int, w: int) -> int:
        return int((self.words[w], self.nodes[part].type_id) in self.walk.sims["type"])

    def hit(self, part: int, w: int, text: Column) -> Column:
        if w in self.by_text(part):
            return F.array_contains(self.nodes[part].tokens(text), self.words[w]).cast("bigint")
        return F.lit(self.by_type(part, w)).cast("bigint")

    # -- rows of the parts

    def frame(self, part: int) -> DataFrame:
        """``id`` (none of rows), hits ``h<w>``, hits and attributes of the literals ``l<w>``, ends ``u<edge>`` named in the row, and
        ``d<edge>``: the sources of edges that lead here."""
        p, row = self.nodes[part], part in self.rows
        end = lambda e, ident: e.plain_end if row else ident
        columns = [] if row else [p.ident.alias("id")]
        columns += [end(self.edges[k], self.edges[k].dst_ident).alias(f"u{k}") for k in self.up(part)]
        columns += [end(e, e.src_ident).alias(f"d{k}") for k, e in enumerate(self.edges) if e.dst == part and k in self.down(e.src)]
        held = [(k, e, end(e, e.dst_ident)) for k, e in enumerate(self.edges) if e.src == part and e.dst in self.literal]
        for w in self.places:
            texts = [F.when(value.isNotNull(), F.lit(self.attr(k, w)) + self.hit(e.dst, w, value)).otherwise(0) for k, e, value in held]
            columns += [self.hit(part, w, p.text).alias(f"h{w}"), reduce(Column.__add__, texts, F.lit(0).cast("bigint")).alias(f"l{w}")]
        return (p.plain if row else p.table).select(*columns)

    def _joined(self, df: DataFrame, k: int, ends: DataFrame, names: list[str]) -> DataFrame:
        """``df`` with ``names`` of the edge's end (as ``<name>_<edge>``; null if it is no node). What all ends have alike is not joined."""
        alike = ends.select(*names).distinct().limit(2).collect()
        if len(alike) == 1:
            ids = few(ends.select(F.col("id").alias("end")), ROOT_ROWS)
            df = df.join(ids, df[f"u{k}"] == ids["end"], "left")
            return df.withColumns({f"{c}_{k}": F.when(F.col("end").isNotNull(), F.lit(alike[0][c])) for c in names}).drop("end")
        ends = few(ends.select(F.col("id").alias("end"), *(F.col(c).alias(f"{c}_{k}") for c in names)), TAIL_ROWS)
        return df.join(ends, df[f"u{k}"] == ends["end"], "left").drop("end")

    def _grouped(self, df: DataFrame, k: int, sums: dict[str, Column]) -> DataFrame:
        """``df`` (id, ..) with the number ``c_<edge>`` of a node's neighbours by a ``down`` edge and the ``sums`` over them."""
        near = self.frames[self.edges[k].dst].where(F.col(f"d{k}").isNotNull())
        near = near.groupBy(F.col(f"d{k}").alias("near")).agg(F.count(F.lit(1)).alias(f"c_{k}"), *(F.sum(c).alias(name) for name, c in sums.items()))
        return df.join(near, df["id"] == near["near"], "left").drop("near").fillna(0, [f"c_{k}", *sums])

    def table(self) -> DataFrame:
        names = {x: [f"{x}{w}" for w in self.places] for x in "hv"}
        plain = [i for i in range(len(self.nodes)) if i not in self.literal and i not in self.rows]
        self.frames = {i: self.frame(i) for i in (*plain, *self.rows)}
        hits = dict(self.frames)
        # v: a node's paths of up to two nodes; of rows, without those to nodes that lead back to them
        for i in (*self.rows, *plain):
            df, row = self.frames[i], i in self.rows
            total = {w: F.col(f"h{w}") + F.col(f"l{w}") for w in self.places}
            for k in self.up(i):
                if row and self.back(k):
                    continue
                df = self._joined(df, k, hits[self.edges[k].dst], names["h"])
                total = {w: x + F.coalesce(F.col(f"h{w}_{k}") + self.attr(k, w), F.lit(0)) for w, x in total.items()}
            if row:
                self.frames[i] = df.select(*hits[i].columns, *(x.alias(f"v{w}") for w, x in total.items()))
                continue
            for k in self.down(i):
                # of rows, what a root needs later is added up in the same pass
                near = {f"h{w}_{k}": F.col(f"h{w}") for w in self.places} | ({f"v{w}_{k}": F.col(f"v{w}") for w in self.places} if self.edges[k].dst in self.rows else {})
                df = self._grouped(df, k, near)
                total = {w: x + F.col(f"h{w}_{k}") + F.col(f"c_{k}") * self.attr(k, w) for w, x in total.items()}
            kept = [c for k in self.down(i) if self.edges[k].dst in self.rows for c in (f"c_{k}", *(f"v{w}_{k}" for w in self.places))]
            hits[i] = store(df.select(*hits[i].columns, *kept, *(x.alias(f"v{w}") for w, x in total.items())))
        self.frames |= {i: hits[i] for i in plain}
        out = [self._roots(i, names["v"]) for i in (*plain, *self.rows)]
        for i in self.literal:
            if self.by_text(i):
                rows = self.nodes[i].rows if self.nodes[i].plain is None else self.nodes[i].plain
                out.append(self._numbers(i, rows, {w: self.hit(i, w, F.col("text")) for w in self.places}))
        return store(reduce(DataFrame.unionByName, out))

    def _roots(self, i: int, values: list[str]) -> DataFrame:
        df, row = self.frames[i], i in self.rows
        total = {w: F.col(f"h{w}") + F.col(f"l{w}") for w in self.places}
        for k in self.up(i):
            df = self._joined(df, k, self.frames[self.edges[k].dst], values)
            # the end leads back here once
            less = lambda w, k=k: F.lit(sum(self.attr(j, w) for j in self.back(k))) + F.col(f"h{w}") * len(self.back(k))
            total = {w: x + F.coalesce(F.col(f"v{w}_{k}") + self.attr(k, w) - less(w), F.lit(0)) for w, x in total.items()}
        for k in self.down(i):
            of_rows = self.edges[k].dst in self.rows
            if not of_rows:
                df = self._grouped(df, k, {f"v{w}_{k}": F.col(f"v{w}") for w in self.places})
            # each neighbour leads back here once; rows were counted without that
            for w in self.places:
                each = F.lit(self.attr(k, w))
                if self.back(k) and not of_rows:
                    each = each - sum(self.attr(j, w) for j in self.back(k)) - F.col(f"h{w}")
                total[w] = total[w] + F.col(f"v{w}_{k}") + F.col(f"c_{k}") * each
        return self._numbers(i, df, total)

    def _numbers(self, i: int, df: DataFrame, total: dict[int, Column]) -> DataFrame:
        rows = df.select(*(x.cast("bigint").alias(f"n{w}") for w, x in total.items()))
        rows = rows.where(reduce(Column.__or__, [F.col(c) > 0 for c in rows.columns]))
        return rows.groupBy(*rows.columns).agg(F.count(F.lit(1)).alias("m")).select(F.lit(self.nodes[i].type_id).alias("root_type"), *rows.columns, "m")
