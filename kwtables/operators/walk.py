"""Postings of a query's words by walks over the schema: only the tables on a path from a possible root to a word are read.

On the driver, label paths are followed backward from the parts of the graph (the rules' nodes) that hold a word, by its
texts, type or attribute. Root parts that cannot reach every word are left out, which changes no answer. Each label path
left is one chain of equality joins over the rules' edges; its pattern is known beforehand, so rows carry node ids only.
Nothing of the graph is written.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graph import ATTRS, SCHEMA_ROWS, EdgePart, KnowledgeGraph, NodePart, no_key_twice
from .index import POSTING_COLUMNS, PathIndex, enumerate_paths, with_patterns
from .lineage import store

#: Roots that reach all words are broadcast up to this many rows.
ROOT_ROWS = 2_000_000
#: Ends of a route that one table's rows tell are broadcast up to this many rows.
TAIL_ROWS = 400_000


def schema_patterns(graph: KnowledgeGraph, d: int) -> DataFrame:
    """The pattern dictionary of every label path that the rules allow; ids in order of the label text, as in a stored index."""
    nodes, edges = graph.parts
    names = {r["type_id"]: r["type_name"] for r in graph.types.collect()}
    attrs = {r["attr_id"]: r["attr_name"] for r in graph.attrs.collect()}
    level, labels = {((p.type_id,), i) for i, p in enumerate(nodes)}, set()
    for n in range(1, d + 1):
        for seq, _ in level:
            labels |= {(seq, False)} | ({(seq[:-1], True)} if n > 1 else set())
        if len(labels) > SCHEMA_ROWS:
            raise ValueError(f"more than {SCHEMA_ROWS} label paths")
        level = {((*seq, e.attr_id, nodes[e.dst].type_id), e.dst) for seq, at in level for e in edges if e.src == at}
    text = lambda seq: ".".join(names[x] if i % 2 == 0 else attrs[x] for i, x in enumerate(seq))
    rows = sorted((text(seq), on_edge, seq) for seq, on_edge in labels)
    table = [(i, list(seq), label, seq[0], len(seq) // 2 + 1, on_edge) for i, (label, on_edge, seq) in enumerate(rows, 1)]
    return graph.types.sparkSession.createDataFrame(table, "pattern_id int, labels array<int>, label string, root_type int, len int, ends_on_edge boolean")


@dataclass(frozen=True)
class WalkedIndex(PathIndex):
    """A path index of which nothing is written: postings of words are walked, all postings come from the lazy paths.

    A query's postings may leave out roots whose type cannot reach all of its words; ``whole`` keeps them.
    """

    ids: dict = field(default_factory=dict, compare=False)

    def postings(self, words: list[str] | None = None, whole: bool = True) -> DataFrame:
        return super().postings() if words is None else Walk(self, words, whole).postings()

    def scan(self, words: list[str]) -> DataFrame:
        return self.postings(words, whole=False)

    def path_counts(self, words: list[str]) -> DataFrame | None:
        from .root_counts import path_counts

        known = self.facts.setdefault("path_counts", {})
        if tuple(words) not in known:
            known[tuple(words)] = path_counts(self, words)
        return known[tuple(words)]

    def list_sizes(self, words: list[str]) -> list[int]:
        words = list(dict.fromkeys(words))
        counted = self.path_counts(words)
        if counted is None:
            return super().list_sizes(words)
        row = counted.agg(*(F.sum(F.col(f"n{i}").cast("decimal(38,0)") * F.col("m")).alias(f"n{i}") for i in range(len(words)))).first()
        return [int(n) for n in row if n]

    def pattern_list(self, word: str, root: int | None = None, root_type: int | None = None) -> DataFrame:
        """A label path is met or not: no key of a row is made to tell, unless of the rows of ``root``."""
        walk = Walk(self, [word], True)
        met = [walk.heads(word, r, root).limit(1).select(F.lit(walk.pattern(r)).alias("pattern_id"), F.lit(walk.type_of(r)).alias("root_type")) for r in walk.chosen(word, None, root, root_type)]
        return reduce(DataFrame.unionByName, met).distinct() if met else walk.empty().select("pattern_id", "root_type")

    def roots(self, word: str, pattern: int | None = None, root_type: int | None = None) -> DataFrame:
        walk = Walk(self, [word], True)
        routes = walk.chosen(word, pattern, None, root_type)
        rows = [h.select(F.col("id").alias("root"), F.lit(t).alias("root_type")) for h, t in walk.all_heads(word, routes)]
        if len(routes) == 1 and walk.open(word, routes[0]):
            return rows[0]  # each row is one root
        return reduce(DataFrame.unionByName, rows).distinct() if rows else walk.empty().select("root", "root_type")

    def word_paths(self, word: str, pattern: int | None = None, root: int | None = None) -> DataFrame:
        out = Walk(self, [word], True, root).postings()
        for name, value in (("pattern_id", pattern), ("root", root)):
            if value is not None:
                out = out.where(F.col(name) == value)
        return out

    def end_root(self, word: str, pattern: int | None = None, least: bool = False) -> int | None:
        """The greatest root that reaches a word (by one pattern), or the least above zero.

        Keys of rows grow with the value that they are made of, so only the rows of the last such value need theirs.
        """
        walk, found, open_ = Walk(self, [word], True), [], {}
        best, end = (F.min, min) if least else (F.max, max)
        for r in walk.chosen(word, pattern):
            made = walk.heads(word, r) if walk.open(word, r) else None
            if made is None:
                found.append(walk.heads(word, r, keys=True))
            else:
                open_.setdefault(r.parts[0], []).append((r, made))
        for part, routes in open_.items():
            value = reduce(DataFrame.unionByName, [made for _, made in routes]).where("id >= 0").agg(best("id")).first()[0]
            rows = lambda at, routes=routes: reduce(DataFrame.unionByName, [walk.heads(word, r, keys=True, made=at) for r, _ in routes])
            near = None if value is None else rows(value).where("id > 0").agg(best("id")).first()[0]
            # hashed keys are below zero: they count where the last value has no other
            found.append(rows(None) if near is None else self.patterns.sparkSession.range(near, near + 1))
        if not found:
            return None
        every = reduce(DataFrame.unionByName, [f.select("id") for f in found])
        return (every.where("id > 0") if least else every).agg(best("id")).first()[0]


def walked_index(graph: KnowledgeGraph, d: int = 3) -> WalkedIndex:
    """The index of a graph with parts. Subtrees are always checked: to find the check idle, every edge would be read."""
    if graph.parts is None or graph.ranks is not None:
        raise ValueError("walks need a graph built by rules, each with one type, and equal ranks")
    patterns = schema_patterns(graph, d)
    ids = {(tuple(r["labels"]), r["ends_on_edge"]): r["pattern_id"] for r in patterns.collect()}
    return WalkedIndex(graph, d, with_patterns(enumerate_paths(graph, d), patterns, F.broadcast), patterns, facts={"check": True}, ids=ids)


@dataclass
class Route:
    """A label path: the parts of its nodes from the root to the end, the edges between, whether the last edge is the match."""

    parts: tuple[int, ...]
    edges: tuple[int, ...]
    on_edge: bool


class Walk:
    """The label paths of some words, and the postings along them."""

    def __init__(self, index: WalkedIndex, words: Iterable[str], whole: bool, root: int | None = None) -> None:
        """``root``: the only one that is asked for; rows of other keys may be left out."""
        self.index, self.words, self.d, self.root = index, list(dict.fromkeys(words)), index.d, root
        self.nodes: list[NodePart]
        self.edges: list[EdgePart]
        self.nodes, self.edges = index.graph.parts
        self.sims = {}
        for kind in ("type", "attr"):
            rows = getattr(index.graph, f"{kind}s").select(f"{kind}_id", "tokens").collect()  # the schema's size
            self.sims[kind] = {(w, r[0]): 1.0 / len(r[1]) for r in rows for w in r[1]}
        self.in_text = self._texts()
        self.routes = {w: self._routes(w) for w in self.words}
        if not whole:
            common = set.intersection(*({r.parts[0] for r in routes} for routes in self.routes.values()))
            self.routes = {w: [r for r in routes if r.parts[0] in common] for w, routes in self.routes.items()}

    def _texts(self) -> set[tuple[str, int]]:
        """(word, part) wherever a text of the part holds the word: one pass over the texts alone, no keys."""
        probes = []
        for i, p in enumerate(self.nodes):
            own = [w for w in self.words if not p.digits or w.isdigit()]
            if own:
                held = F.array_intersect(p.tokens(F.col("text")), F.array(*map(F.lit, own)))
                probes.append(p.texts.select(F.lit(i).alias("part"), F.explode(held).alias("word")))
        return {(r["word"], r["part"]) for r in reduce(DataFrame.unionByName, probes).distinct().collect()} if probes else set()

    def _routes(self, word: str) -> list[Route]:
        level = [Route((i,), (), False) for i, p in enumerate(self.nodes) if (word, i) in self.in_text or (word, p.type_id) in self.sims["type"]]
        out: list[Route] = []
        for n in range(1, self.d + 1):
            if n == 2:
                level += [Route((e.src, e.dst), (k,), True) for k, e in enumerate(self.edges) if (word, e.attr_id) in self.sims["attr"]]
            out += level
            level = [Route((e.src, *r.parts), (k, *r.edges), r.on_edge) for r in level for k, e in enumerate(self.edges) if e.dst == r.parts[0] and not self._returns(e, r)]
        return out

    def _returns(self, e: EdgePart, r: Route) -> bool:
        """Whether ``e`` and the route's first edge, read from one row of a table, lead back to where they came from."""
        if not r.edges:
            return False
        f = self.edges[r.edges[0]]
        middle = self.nodes[e.dst]
        return middle.unique and middle.source == e.dst_source == f.src_source and e.src_source == f.dst_source

    def look_for_unique_keys(self) -> None:
        """Finds the tables on the routes whose keys never repeat: their nodes are rows, so that fewer joins are needed."""
        met = {i for routes in self.routes.values() for r in routes for i in r.parts}
        open_ = {self.nodes[i].keyed_by: self.nodes[i].keys for i in met if not self.nodes[i].unique and self.nodes[i].keys is not None}
        own = {by for by, keys in open_.items() if no_key_twice(keys)}
        self.nodes = [replace(p, unique=p.unique or i in met and p.keyed_by in own) for i, p in enumerate(self.nodes)]
        self.routes = {w: [r for r in routes if not any(self._returns(self.edges[e], Route(r.parts[i + 1 :], r.edges[i + 1 :], r.on_edge)) for i, e in enumerate(r.edges))] for w, routes in self.routes.items()}

    # -- rows

    def _present(self, df: DataFrame, part: int, column: str, source: tuple[str, str]) -> DataFrame:
        """``df`` where ``column`` is a node of the part, as often as the node is a row; ids of the node's own row need no look."""
        p = self.nodes[part]
        if p.unique and p.source == source:
            return df
        return df.join(p.rows.select(F.col("node_id").alias(column)), column)

    def _start(self, word: str, part: int, rows: DataFrame | None = None) -> DataFrame:
        """``n0, sim`` of the part's nodes (or of ``rows``) that hold the word."""
        p, named = self.nodes[part], self.sims["type"].get((word, self.nodes[part].type_id))
        rows = p.rows if rows is None else rows
        if (word, part) not in self.in_text:
            return rows.select(F.col("node_id").alias("n0"), F.lit(named).alias("sim"))
        tokens = p.tokens(F.col("text"))
        own = F.when(F.array_contains(tokens, word), F.lit(1.0) / F.size(tokens))
        sims = rows.select(F.col("node_id").alias("n0"), (own if named is None else F.greatest(own, F.lit(named))).alias("sim")).where("sim IS NOT NULL")
        # nodes of one id hold a word together
        return sims if p.unique else self._present(sims.groupBy("n0").agg(F.max("sim").alias("sim")), part, "n0", ("", ""))

    def _rows(self, word: str, r: Route, known: dict, roots: DataFrame | None) -> DataFrame:
        """``n<k>.. n0, sim`` of a route, n<k> the root; ``known`` shares what routes have in common."""

        def chain(parts: tuple[int, ...], edges: tuple[int, ...], last: bool) -> DataFrame:
            key = (parts, edges, last and (roots is not None or self.root is not None))
            if key not in known:
                known[key] = step(parts, edges, last)
            return known[key]

        def only(df: DataFrame, column: str, last: bool) -> DataFrame:
            return df if roots is None or not last else df.join(roots.select(F.col("root").alias(column)), column, "left_semi")

        def step(parts: tuple[int, ...], edges: tuple[int, ...], last: bool) -> DataFrame:
            k, made = len(edges), self._made(parts[0]) if last else None
            if k == 0:
                return only(self._start(word, parts[0], self._node_rows(parts[0], made)), "n0", last)
            e = self.edges[edges[0]]
            links = self._edge_rows(edges[0], made)
            if k == 1 and r.on_edge:
                sim = self.sims["attr"][word, e.attr_id]
                df = only(links.where("src <> dst").select(F.col("src").alias("n1"), F.col("dst").alias("n0"), F.lit(sim).alias("sim")), "n1", last)
                df = self._present(df, parts[1], "n0", e.dst_source)
            elif k == 1 and self.root is None and self.nodes[parts[1]].unique and e.dst_source == self.nodes[parts[1]].source and (e.dst_source[1] == "literal" or (word, parts[1]) not in self.in_text):
                df = only(self._one_row(word, e, links), "n1", last)
            else:
                tail = chain(parts[1:], edges[1:], False)
                if self.root is None and (not last or roots is None) and self._of_one_table(word, parts[1:], edges[1:]):
                    tail = few(tail, TAIL_ROWS)
                df = only(tail.join(links.select(F.col("src").alias(f"n{k}"), F.col("dst").alias(f"n{k - 1}")), f"n{k - 1}"), f"n{k}", last)
                for i in range(k):
                    if self._may_meet(parts[0], parts[k - i]):
                        df = df.where(f"n{k} <> n{i}")
            return self._present(df, parts[0], f"n{k}", e.src_source)

        return chain(r.parts, r.edges, True)

    def _one_row(self, word: str, e: EdgePart, links: DataFrame) -> DataFrame:
        """``n1, n0, sim`` of an edge whose end is known from the same row: a row's literal, or a row that needs no look."""
        if (word, e.dst) not in self.in_text:
            return links.select(F.col("src").alias("n1"), F.col("dst").alias("n0"), F.lit(self.sims["type"][word, self.nodes[e.dst].type_id]).alias("sim"))
        # a literal's id has its source's
        return self._start(word, e.dst).select(F.shiftright(-F.col("n0"), ATTRS.bit_length() - 1).alias("n1"), "n0", "sim")

    def _of_one_table(self, word: str, parts: tuple[int, ...], edges: tuple[int, ...]) -> bool:
        """Whether the rows of a route's end are found without a join, so that counting them is a scan."""
        if not edges:
            return self.nodes[parts[0]].unique and self.nodes[parts[0]].made is None
        p, q, e = self.nodes[parts[0]], self.nodes[parts[1]], self.edges[edges[0]]
        return len(edges) == 1 and p.unique and p.made is None and p.source == e.src_source and q.unique and e.dst_source == q.source and (e.dst_source[1] == "literal" or (word, parts[1]) not in self.in_text)

    @staticmethod
    def _may_meet(a: int, b: int) -> bool:
        return a == b

    def _made(self, part: int) -> int | None:
        return None if self.root is None else self.nodes[part].made_of(self.root)

    def _node_rows(self, part: int, made: int | None) -> DataFrame:
        p = self.nodes[part]
        return p.rows if made is None or p.at is None else p.at(made)

    def _edge_rows(self, edge: int, made: int | None) -> DataFrame:
        e = self.edges[edge]
        return e.rows if made is None or e.at is None else e.at(made)

    # -- roots alone

    def type_of(self, r: Route) -> int:
        return self.nodes[r.parts[0]].type_id

    def chosen(self, word: str, pattern: int | None = None, root: int | None = None, root_type: int | None = None) -> list[Route]:
        """The word's routes of a pattern, of a root type, or from the parts that a row's id does not rule out."""
        out = [r for r in self.routes[word] if pattern in (None, self.pattern(r)) and root_type in (None, self.type_of(r))]
        held = [i for i, p in enumerate(self.nodes) if root is not None and p.made_of(root) is not None]
        return [r for r in out if not held or r.parts[0] in held]

    def open(self, word: str, r: Route) -> bool:
        """Whether the route's roots are rows that are found without their made keys."""
        p = self.nodes[r.parts[0]]
        if p.made is None or len(set(r.parts)) < len(r.parts):
            return False
        if not r.edges:
            return (word, r.parts[0]) not in self.in_text
        e = self.edges[r.edges[0]]
        return e.made is not None and e.src_source == p.source

    def by_ends(self, word: str, r: Route) -> bool:
        """Whether the roots' keys can be made from the ends of the route's first edge."""
        if not self.open(word, r) or not r.edges or self.edges[r.edges[0]].sources is None:
            return False
        e, q = self.edges[r.edges[0]], self.nodes[r.parts[1]]
        return not (len(r.edges) == 1 and r.on_edge and q.unique and q.source == e.dst_source)

    def all_heads(self, word: str, routes: list[Route]) -> list[tuple[DataFrame, int]]:
        """``id`` of the routes' roots with their type; row keys are made once for all routes that leave by one edge."""
        out, shared = [], {}
        for r in routes:
            if self.by_ends(word, r):
                shared.setdefault(r.edges[0], []).append(r)
            else:
                out.append((self.heads(word, r, keys=True), self.type_of(r)))
        for edge, own in shared.items():
            ends = reduce(DataFrame.unionByName, [self.heads(word, r, keys=True, ends_only=True) for r in own])
            out.append((self.edges[edge].sources(few(store(ends.distinct()))), self.type_of(own[0])))
        return out

    def heads(self, word: str, r: Route, root: int | None = None, keys: bool = False, made: int | None = None, ends_only: bool = False) -> DataFrame:
        """``id`` of the route's roots, some more than once: of all, of ``root`` or of the row keys of one ``made`` value. Without
        ``keys`` and a root, the made values of open routes. Nodes beyond the root are only asked for, not kept.
        ``ends_only``: ``node_id`` of the ends of the first edge instead, some more than once.
        """
        if keys and root is None and made is None and not ends_only and self.by_ends(word, r):
            return self.all_heads(word, [r])[0][0]
        if root is not None:
            made = self.nodes[r.parts[0]].made_of(root)
        end, open_ = len(r.edges), not keys and root is None and self.open(word, r)

        def reach(i: int) -> DataFrame:
            p = self.nodes[r.parts[i]]
            own = made if i == 0 else None
            if i == end:
                return p.made.select(F.col("made").alias("id")) if open_ and i == 0 else self._start(word, r.parts[i], self._node_rows(r.parts[i], own)).select(F.col("n0").alias("id"))
            e = self.edges[r.edges[i]]
            rows = e.made.select(F.col("made").alias("src"), "dst") if open_ and i == 0 else self._edge_rows(r.edges[i], own)
            if i == end - 1 and r.on_edge:
                rows = rows if open_ and i == 0 else rows.where("src <> dst")
                q = self.nodes[r.parts[end]]
                ends = None if q.unique and q.source == e.dst_source else q.rows.select("node_id")
            else:
                ends = reach(i + 1).withColumnRenamed("id", "node_id")
            if ends_only and i == 0:
                return ends
            if ends is not None:
                # row nodes are the many: what they lead to is written once, so that it can be broadcast
                ends = few(store(ends.distinct())) if p.made is not None and made is None else ends
                rows = rows.join(ends, rows["dst"] == ends["node_id"], "left_semi")
            out = rows.select(F.col("src").alias("id"))
            if p.unique and p.source == e.src_source:
                return out
            return out.join(p.rows.select(F.col("node_id").alias("id")), "id", "left_semi")

        if len(set(r.parts)) < len(r.parts):
            out = self._rows(word, r, {}, None).select(F.col(f"n{end}").alias("id"))
        else:
            out = reach(0)
        return out if root is None else out.where(F.col("id") == root)

    def pattern(self, r: Route) -> int:
        labels = self._labels(r)
        return self.index.ids[tuple(labels[:-1] if r.on_edge else labels), r.on_edge]

    def _labels(self, r: Route) -> list[int]:
        labels = [self.type_of(r)]
        for e, i in zip(r.edges, r.parts[1:], strict=True):
            labels += [self.edges[e].attr_id, self.nodes[i].type_id]
        return labels

    def _posting(self, word: str, r: Route, df: DataFrame) -> DataFrame:
        k, pattern = len(r.edges), self.pattern(r)
        attrs = F.array(*(F.lit(self.edges[e].attr_id) for e in r.edges)).cast("array<int>")
        return df.select(F.lit(word).alias("word"), F.lit(pattern).alias("pattern_id"), F.col(f"n{k}").alias("root"), F.lit(self.type_of(r)).alias("root_type"), F.array(*(F.col(f"n{i}") for i in range(k, -1, -1))).alias("nodes"), attrs.alias("attrs"), F.lit(k + 1).alias("len"), F.lit(1.0).alias("pr"), "sim")

    def of(self, word: str, roots: DataFrame | None = None) -> DataFrame:
        """The word's postings, of ``roots`` (root) alone if given."""
        known: dict = {True: {}, False: {}}
        rows = [self._posting(word, r, self._rows(word, r, known[r.on_edge], roots)) for r in self.routes[word]]
        return reduce(DataFrame.unionByName, rows) if rows else self.empty()

    def empty(self) -> DataFrame:
        spark = self.index.patterns.sparkSession
        return spark.createDataFrame([], "word string, pattern_id int, root bigint, root_type int, nodes array<bigint>, attrs array<int>, len int, pr double, sim double").select(*POSTING_COLUMNS)

    def postings(self) -> DataFrame:
        return reduce(DataFrame.unionByName, [self.of(w) for w in self.words])

    def rooted(self) -> DataFrame:
        """Postings under the roots that reach every word: the roots are found word by word and written (two numbers each),
        words of texts alone first, so that the many roots of a common word are never gathered."""
        common = lambda w: any(r.on_edge or (w, self.nodes[r.parts[-1]].type_id) in self.sims["type"] for r in self.routes[w])
        self.look_for_unique_keys()
        roots = None
        for w in sorted(self.words, key=common):
            roots = few(store(self.of(w, roots).select("root", "root_type").distinct()))
        return reduce(DataFrame.unionByName, [self.of(w, roots) for w in self.words])


def few(roots: DataFrame, most: int = ROOT_ROWS) -> DataFrame:
    return F.broadcast(roots) if roots.count() <= most else roots
