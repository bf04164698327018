"""Typed knowledge graphs from relational tables, by declarative rules."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import tokenize

LITERAL_TYPE = "Text"
#: Entity ids are key * KINDS + code of the kind; occurrence literals are -(source id * ATTRS + attribute id).
KINDS, ATTRS = 64, 64
SCOPES = ("occurrence", "attribute", "value")
#: A graph schema (types, attributes, patterns) is broadcast up to this many rows.
SCHEMA_ROWS = 1_000_000
#: Places that a row key has room for beside the key it is made of.
ROW_PLACES = 65536


@dataclass(frozen=True)
class NodeRule:
    """Entities: one for each row of ``table``. ``type_expr`` overrides the type name by a column's value."""

    kind: str
    table: str
    key: str
    text: str
    type_expr: str | None = None


@dataclass(frozen=True)
class EdgeRule:
    """Edges ``attr`` from entity kind ``src`` to ``dst``; ``inverse`` turns the table's reference around."""

    attr: str
    table: str
    src: str
    src_key: str
    dst: str
    dst_key: str
    explode: bool = False


@dataclass(frozen=True)
class LiteralRule:
    """Plain-text values of ``attr``: a dummy entity for each."""

    attr: str
    table: str
    src: str
    src_key: str
    value: str


@dataclass(frozen=True)
class GraphSpec:
    nodes: tuple[NodeRule, ...]
    edges: tuple[EdgeRule, ...]
    literals: tuple[LiteralRule, ...] = ()
    derived: dict[str, Callable[[SparkSession, str], DataFrame]] = field(default_factory=dict, hash=False)
    prose: bool = False
    #: (table, column) pairs whose values never repeat, whatever the data.
    unique: frozenset[tuple[str, str]] = frozenset()
    #: (table, made row key) to the column that the key is made of by ``keyed`` with the row's place among its equals.
    placed: dict[tuple[str, str], str] = field(default_factory=dict, hash=False)


@dataclass(frozen=True)
class NodePart:
    """The nodes of one rule, all of one type. ``texts`` reads their texts alone (perhaps more: rows without a key)."""

    type_id: int
    rows: DataFrame
    texts: DataFrame
    tokens: Callable[[Column], Column]
    #: Each node is one row, and edges of the same table leave from no other id.
    unique: bool = False
    #: Texts are whole numbers.
    digits: bool = False
    source: tuple[str, str] = ("", "")
    #: Where nodes are keyed by row, or are such rows' literals: the table without made keys (literals: ``text``), the rows that get
    #: no key, and ``number, n`` of the keys.
    plain: DataFrame | None = None
    unkeyed: DataFrame | None = None
    plain_keys: DataFrame | None = None
    #: Where nodes are keyed by row: what an id adds to its key times KINDS, the values that the keys are made of (``made``, a row for
    #: each node) and the ``rows`` of one such value.
    code: int = 0
    made: DataFrame | None = None
    at: Callable[[int], DataFrame] | None = None
    #: The key (``key``) of every row of the table that nodes, or the sources of literals, come from, and that table and column.
    keys: DataFrame | None = None
    keyed_by: tuple[str, str] = ("", "")
    #: Where no key is made: the rows of the table that have one, and the node's id over them; the text over the rule's table.
    table: DataFrame | None = None
    ident: Column | None = None
    text: Column | None = None

    def made_of(self, node: int) -> int | None:
        """The value that a row node's key is made of; None if the id does not tell, as hashed keys."""
        key, code = divmod(node, KINDS)
        return key // ROW_PLACES if self.made is not None and code == self.code and key >= 0 else None


@dataclass(frozen=True)
class EdgePart:
    """The edges of one rule, between the nodes of two parts (given by their places in the list of parts)."""

    attr_id: int
    src: int
    dst: int
    rows: DataFrame
    #: Table and column that the sources' and the ends' ids come from.
    src_source: tuple[str, str] = ("", "")
    dst_source: tuple[str, str] = ("", "")
    #: Where one end is a row without a made key: the rows with that end null, and the other end as an expression of the plain table.
    plain: DataFrame | None = None
    plain_end: Column | None = None
    #: Where sources are keyed by row: ``made, dst`` without made keys (None if the ends need the key), and the ``rows`` of one made value.
    made: DataFrame | None = None
    at: Callable[[int], DataFrame] | None = None
    #: As ``made``: ``id`` of the sources whose ends are among given ones (``node_id``, no id twice).
    sources: Callable[[DataFrame], DataFrame] | None = None
    #: The ids of both ends (literals: the text) over the rule's table, where that end has no made key.
    src_ident: Column | None = None
    dst_ident: Column | None = None


@dataclass
class KnowledgeGraph:
    """``nodes(node_id, node_key, type_id, text, tokens, is_literal)``, ``edges(src, attr_id, dst)``, ``types``, ``attrs``; optional ``ranks(node_id, pr)``.

    ``parts``: the same nodes and edges rule by rule, if each rule's nodes have one type; walks then read only the tables
    that a path of the schema names.
    """

    nodes: DataFrame
    edges: DataFrame
    types: DataFrame
    attrs: DataFrame
    ranks: DataFrame | None = None
    parts: tuple[list[NodePart], list[EdgePart]] | None = None

    def with_ranks(self, ranks: DataFrame) -> KnowledgeGraph:
        return KnowledgeGraph(self.nodes, self.edges, self.types, self.attrs, ranks)

    def texts(self, label_paths: list[list[int]]) -> DataFrame:
        """``node_id, text`` of the nodes that paths of these labels (type, attribute, type, ..) can hold, perhaps of more."""
        if self.parts is None:
            return self.nodes.select("node_id", "text")
        nodes, edges = self.parts
        held = {i for i, p in enumerate(nodes) if p.type_id in {path[0] for path in label_paths}}
        for path in label_paths:
            for at in range(1, len(path), 2):
                ends = {e.dst for e in edges if e.attr_id == path[at]}
                held |= {i for i in ends if at + 1 == len(path) or nodes[i].type_id == path[at + 1]}
        return reduce(DataFrame.unionByName, [nodes[i].rows.select("node_id", "text") for i in sorted(held)])

    def ranked_nodes(self) -> DataFrame:
        """Nodes with ``pr``; importance is 1 everywhere unless ranks are given."""
        slim = self.nodes.select("node_id", "type_id")
        return slim.withColumn("pr", F.lit(1.0)) if self.ranks is None else slim.join(self.ranks.select("node_id", "pr"), "node_id")

    def stored(self) -> KnowledgeGraph:
        """The same graph, written once and read from files."""
        from ..operators.lineage import store

        return KnowledgeGraph(store(self.nodes), store(self.edges), store(self.types), store(self.attrs), store(self.ranks) if self.ranks is not None else None)


def lineitem_keyed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items with a surrogate key: the order's key and the place among the order's rows, a window of a few rows."""
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    order = [F.col(c) for c in sorted(rows.columns)]
    place = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*order))
    return rows.withColumn("place", place).withColumn("l_key", keyed("l_orderkey", F.col("place"), ROW_PLACES, F.col("l_orderkey"), F.col("place"))).drop("place")


def keyed(key: str, place: Column, room: int, *whole: Column) -> Column:
    """``key * room + place`` while the place fits into ``room``, else a negative key from a hash of the ``whole`` key, which no room bounds."""
    far = -F.shiftrightunsigned(F.xxhash64(*whole), 8) - 1
    return F.when((place >= 0) & (place < room), F.col(key) * room + place).otherwise(far)


def keys_where(rows: DataFrame, made: str, key: str, mark: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``key`` of the rows that ``mark`` gives a true ``held``: the keys of ``lineitem_keyed``, from less than whole rows.

    Rows are placed by the first two columns of their order, doubles rounded to floats, which keeps their order. Where that leaves
    held and other rows equal, the rows of that ``made`` value are read again and placed by all columns. Places are written once.
    """
    from ..operators.lineage import store
    from ..operators.walk import few

    order, kinds = sorted(rows.columns), dict(rows.dtypes)
    first = [(F.col(c).cast("float") if kinds[c] == "double" else F.col(c)).alias(f"at{i}") for i, c in enumerate(order[:2])]
    near = Window.partitionBy("made").orderBy(*(f"at{i}" for i in range(len(first))))
    equal = near.rangeBetween(Window.currentRow, Window.currentRow)
    mixed = F.count(F.lit(1)).over(equal) > F.sum(F.col("held").cast("int")).over(equal)
    marked = mark(rows).select(F.col(made).alias("made"), *first, "held")
    placed = store(marked.select("made", F.row_number().over(near).alias("place"), "held", mixed.alias("mixed")).where("held").select("made", "place", "mixed"))
    open_ = placed.where("mixed").select("made").distinct()
    if not open_.isEmpty():
        open_ = few(store(open_))
        again = rows.join(open_, rows[made].eqNullSafe(open_["made"]), "left_semi")
        place = F.row_number().over(Window.partitionBy(made).orderBy(*order))
        exact = mark(again.withColumn("place", place)).where("held").select(F.col(made).alias("made"), "place")
        placed = placed.join(open_, placed["made"].eqNullSafe(open_["made"]), "left_anti").select("made", "place").unionByName(exact)
    return placed.select(keyed("made", F.col("place"), ROW_PLACES, F.col("made"), F.col("place")).alias(key)).where(f"{key} IS NOT NULL")


def no_key_twice(keys: DataFrame) -> bool:
    """Whether no ``key`` is there twice. Keys that lie dense are counted as bits, so that few bytes are handed on."""
    row = keys.agg(F.count("key").alias("n"), F.min("key").alias("least"), F.max("key").alias("most")).first()
    if row["n"] < 2:
        return True
    if row["most"] - row["least"] > 64 * row["n"]:
        return keys.where("key IS NOT NULL").groupBy("key").count().where("count > 1").isEmpty()
    bits = keys.where("key IS NOT NULL").groupBy(F.bitmap_bucket_number("key").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("key")).alias("bits"))
    return bits.agg(F.sum(F.bitmap_count("bits"))).first()[0] == row["n"]


def row_keys(rows: DataFrame, made: str) -> DataFrame:
    """``number, n``: the digits of each made row key, with 1. Keys have places from 1 on, so counts of ``made`` give them all."""
    counts = rows.groupBy(made).agg(F.count(F.lit(1)).alias("rows"))
    block = counts.select(made, "rows", F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col("rows") - 1) / ROW_PLACES))).alias("block"))
    places = block.select(made, F.explode(F.sequence(F.col("block") * ROW_PLACES + 1, F.least("rows", (F.col("block") + 1) * ROW_PLACES))).alias("place"))
    key = keyed(made, F.col("place").cast("int"), ROW_PLACES, F.col(made), F.col("place").cast("int"))
    return places.select(F.abs(key).alias("number"), F.lit(1).cast("bigint").alias("n"))


def schema_names(names: DataFrame) -> list[str]:
    """The distinct names of a one-column table, sorted; more than SCHEMA_ROWS of them are no schema and raise."""
    rows = names.distinct().limit(SCHEMA_ROWS + 1).collect()
    if len(rows) > SCHEMA_ROWS:
        raise ValueError(f"more than {SCHEMA_ROWS} types or attributes")
    return sorted(r[0] for r in rows if r[0] is not None)


def as_text(column: str) -> str:
    """Rule by which numbers become text alike in every engine."""
    return f"CAST(CAST(ROUND({column}, 2) AS DECIMAL(18,2)) AS STRING)"


_FORWARD_NODES = (
    NodeRule("Region", "region", "r_regionkey", "r_name"),
    NodeRule("Nation", "nation", "n_nationkey", "n_name"),
    NodeRule("Customer", "customer", "c_custkey", "c_name"),
    NodeRule("Supplier", "supplier", "s_suppkey", "s_name"),
    NodeRule("Part", "part", "p_partkey", "p_name"),
    NodeRule("Order", "orders", "o_orderkey", "CAST(o_orderkey AS STRING)"),
    NodeRule("Lineitem", "lineitem", "l_key", "CAST(l_key AS STRING)"),
)
_FORWARD_EDGES = (
    EdgeRule("region", "nation", "Nation", "n_nationkey", "Region", "n_regionkey"),
    EdgeRule("nation", "customer", "Customer", "c_custkey", "Nation", "c_nationkey"),
    EdgeRule("nation", "supplier", "Supplier", "s_suppkey", "Nation", "s_nationkey"),
    EdgeRule("customer", "orders", "Order", "o_orderkey", "Customer", "o_custkey"),
    EdgeRule("order", "lineitem", "Lineitem", "l_key", "Order", "l_orderkey"),
    EdgeRule("part", "lineitem", "Lineitem", "l_key", "Part", "l_partkey"),
    EdgeRule("supplier", "lineitem", "Lineitem", "l_key", "Supplier", "l_suppkey"),
)
_FORWARD_LITERALS = (
    LiteralRule("market segment", "customer", "Customer", "c_custkey", "c_mktsegment"),
    LiteralRule("brand", "part", "Part", "p_partkey", "p_brand"),
    LiteralRule("part type", "part", "Part", "p_partkey", "p_type"),
    LiteralRule("order priority", "orders", "Order", "o_orderkey", "o_orderpriority"),
    LiteralRule("order status", "orders", "Order", "o_orderkey", "o_orderstatus"),
    LiteralRule("return flag", "lineitem", "Lineitem", "l_key", "l_returnflag"),
    LiteralRule("line status", "lineitem", "Lineitem", "l_key", "l_linestatus"),
)
_INVERSE_EDGES = (
    EdgeRule("lines", "lineitem", "Order", "l_orderkey", "Lineitem", "l_key"),
    EdgeRule("orders", "orders", "Customer", "o_custkey", "Order", "o_orderkey"),
    EdgeRule("residents", "customer", "Nation", "c_nationkey", "Customer", "c_custkey"),
    EdgeRule("nations", "nation", "Region", "n_regionkey", "Nation", "n_nationkey"),
)
#: Line items are keyed by their place in the order.
_ROW_KEYS = frozenset({("lineitem", "l_key")})
_PLACED = {("lineitem", "l_key"): "l_orderkey"}
_TYPED_BY = {"Part": "p_brand", "Order": "o_orderpriority", "Customer": "c_mktsegment"}


def _wide(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """Derived tables of the text-heavy profile."""
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    if table == "documents_labelled":
        marks = read("labels").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
        return read("documents").join(marks, "doc_id", "left").withColumn("grade", F.when(F.col("quality") == 1, "good quality").when(F.col("quality") == 0, "poor quality")).withColumn("harm", F.when(F.col("toxic") == 1, "toxic"))
    host = F.regexp_extract("url", r"^https?://([^/?#]+)", 1)
    pages = read("pages").withColumn("site", host).withColumn("site_key", F.shiftrightunsigned(F.xxhash64(host), 8)).withColumn("title", F.regexp_extract("html", r"(?s)<title>(.*?)</title>", 1))
    if table == "pages_read":
        return pages
    if table == "sites":
        return pages.select("site_key", "site").distinct()
    links = pages.select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit(r'href="(/[^"]*)"'), F.lit(1)))).alias("section")).withColumn("section_key", F.shiftrightunsigned(F.xxhash64("section"), 8))
    if table == "page_links":
        return links
    if table == "sections":
        return links.select("section_key", "section").distinct()
    turns = read("conversations")
    if table != "turns":
        return turns.select("conv_id").distinct()
    # turns of equal number are numbered on; a conversation of any length keeps all its turns
    again = F.row_number().over(Window.partitionBy("conv_id", "turn").orderBy("role", "text"))
    numbered = turns.withColumn("again", again)
    return numbered.withColumn("turn_key", keyed("conv_id", F.when(F.col("again") == 1, F.col("turn")).otherwise(F.lit(-1)), 4096, F.col("conv_id"), F.col("turn"), F.col("again"))).drop("again")


def spec_for(profile: str) -> GraphSpec:
    """Rules of the named catalogue profile: forward, linked, many_types, many_types_forward or wide."""
    keyed = {"lineitem": lineitem_keyed}
    if profile == "forward":
        return GraphSpec(_FORWARD_NODES, _FORWARD_EDGES, _FORWARD_LITERALS, keyed, unique=_ROW_KEYS, placed=_PLACED)
    if profile == "linked":
        return GraphSpec(_FORWARD_NODES, _FORWARD_EDGES + _INVERSE_EDGES, _FORWARD_LITERALS, keyed, unique=_ROW_KEYS, placed=_PLACED)
    if profile in ("many_types", "many_types_forward"):
        nodes = tuple(NodeRule(n.kind, n.table, n.key, n.text, _TYPED_BY.get(n.kind)) for n in _FORWARD_NODES)
        return GraphSpec(nodes, _FORWARD_EDGES + (_INVERSE_EDGES if profile == "many_types" else ()), _FORWARD_LITERALS, keyed, unique=_ROW_KEYS, placed=_PLACED)
    if profile == "wide":
        nodes = (
            *_FORWARD_NODES,
            NodeRule("Document", "documents_labelled", "doc_id", "text"),
            NodeRule("Page", "pages_read", "page_id", "title"),
            NodeRule("Site", "sites", "site_key", "site"),
            NodeRule("Section", "sections", "section_key", "section"),
            NodeRule("Utterance", "turns", "turn_key", "text"),
            NodeRule("Conversation", "dialogues", "conv_id", "CAST(conv_id AS STRING)"),
            NodeRule("Event", "events", "event_id", "CAST(event_id AS STRING)"),
            NodeRule("Passage", "benchmark", "item_id", "text"),
        )
        edges = (
            *_FORWARD_EDGES,
            *_INVERSE_EDGES,
            EdgeRule("site", "pages_read", "Page", "page_id", "Site", "site_key"),
            EdgeRule("links to", "page_links", "Page", "page_id", "Section", "section_key"),
            EdgeRule("conversation", "turns", "Utterance", "turn_key", "Conversation", "conv_id"),
            EdgeRule("user", "events", "Event", "event_id", "Customer", "user_id"),
        )
        literals = (
            *_FORWARD_LITERALS,
            LiteralRule("lang", "documents_labelled", "Document", "doc_id", "lang"),
            LiteralRule("source", "documents_labelled", "Document", "doc_id", "source"),
            LiteralRule("quality", "documents_labelled", "Document", "doc_id", "grade"),
            LiteralRule("harm", "documents_labelled", "Document", "doc_id", "harm"),
            LiteralRule("role", "turns", "Utterance", "turn_key", "role"),
            LiteralRule("event type", "events", "Event", "event_id", "event_type"),
            LiteralRule("properties", "events", "Event", "event_id", "get_json_object(props, '$.k')"),
        )
        derived = keyed | {t: (lambda s, d, t=t: _wide(s, d, t)) for t in ("documents_labelled", "pages_read", "sites", "sections", "page_links", "turns", "dialogues")}
        return GraphSpec(nodes, edges, literals, derived, prose=True, unique=_ROW_KEYS, placed=_PLACED)
    raise ValueError(f"unknown profile {profile!r}")


def schema_table(spark: SparkSession, names: list[str], prefix: str) -> DataFrame:
    """Dense ids of schema names with their words; the reserved literal type has none."""
    kind = f"{prefix}_id int, {prefix}_name string"
    table = spark.createDataFrame(list(enumerate(names)), kind)
    words = tokenize(F.col(f"{prefix}_name"))
    return table.withColumn("tokens", F.when(F.col(f"{prefix}_name") == LITERAL_TYPE, F.array().cast("array<string>")).otherwise(words) if prefix == "type" else words)


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def literal_nodes(values: DataFrame, scope: str) -> DataFrame:
    """``values(src, attr_id, attr_name, value)`` with ``node_id`` and ``node_key`` of their dummy entities under ``scope``."""
    if scope not in SCOPES:
        raise ValueError(f"unknown literal scope {scope!r}")
    if scope == "occurrence":
        return values.withColumn("node_id", -(F.col("src") * ATTRS + F.col("attr_id"))).withColumn("node_key", F.concat_ws(".", F.col("src").cast("string"), "attr_name"))
    parts = (["attr_name"] if scope == "attribute" else []) + ["value"]
    return values.withColumn("node_key", F.concat_ws("=", F.lit("literal"), *parts)).withColumn("node_id", F.xxhash64("node_key"))


def build_graph(spark: SparkSession, sf_dir: str, profile: str | GraphSpec = "forward", literal_scope: str = "occurrence") -> KnowledgeGraph:
    """The tables of ``sf_dir`` as a knowledge graph, by the rules of ``profile``."""
    spec = spec_for(profile) if isinstance(profile, str) else profile
    read = lambda t: spec.derived[t](spark, sf_dir) if t in spec.derived else spark.read.parquet(f"{sf_dir}/{t}.parquet")
    code = {n.kind: i + 1 for i, n in enumerate(spec.nodes)}
    ident = lambda kind, key: F.expr(f"CAST({key} AS BIGINT) * {KINDS} + {code[kind]}")

    names = {n.kind for n in spec.nodes if n.type_expr is None}
    for n in spec.nodes:
        if n.type_expr is not None:
            names |= {*schema_names(read(n.table).select(F.expr(n.type_expr))), n.kind}
    type_list = [LITERAL_TYPE, *sorted(names - {LITERAL_TYPE})]
    types, type_id = schema_table(spark, type_list, "type"), {t: i for i, t in enumerate(type_list)}
    attrs = schema_table(spark, sorted({e.attr for e in spec.edges} | {x.attr for x in spec.literals}), "attr")
    if len(spec.nodes) >= KINDS or len({e.attr for e in spec.edges} | {x.attr for x in spec.literals}) > ATTRS:
        raise ValueError(f"ids have room for {KINDS - 1} kinds of entities and {ATTRS} attributes")
    attr_id = {r["attr_name"]: r["attr_id"] for r in attrs.collect()}

    entities = _union([read(n.table).where(f"{n.key} IS NOT NULL").select(ident(n.kind, n.key).alias("node_id"), F.concat_ws("/", F.lit(n.kind), F.expr(f"CAST({n.key} AS STRING)")).alias("node_key"), F.expr(f"COALESCE({n.type_expr}, '{n.kind}')" if n.type_expr else f"'{n.kind}'").alias("type_name"), F.expr(n.text).alias("text")) for n in spec.nodes])
    links = _union([read(e.table).where(f"{e.src_key} IS NOT NULL AND {e.dst_key} IS NOT NULL").select(ident(e.src, e.src_key).alias("src"), F.lit(attr_id[e.attr]).alias("attr_id"), ident(e.dst, e.dst_key).alias("dst")) for e in spec.edges])
    pieces = [entities.withColumn("is_literal", F.lit(False))]
    if spec.literals:
        values = _union([read(x.table).where(f"{x.src_key} IS NOT NULL").select(ident(x.src, x.src_key).alias("src"), F.lit(attr_id[x.attr]).alias("attr_id"), F.lit(x.attr).alias("attr_name"), F.expr(f"CAST({x.value} AS STRING)").alias("value")).where("value IS NOT NULL") for x in spec.literals])
        dummies = literal_nodes(values, literal_scope)
        links = links.unionByName(dummies.select("src", "attr_id", F.col("node_id").alias("dst")))
        own = dummies.select("node_id", "node_key", F.lit(LITERAL_TYPE).alias("type_name"), F.col("value").alias("text"), F.lit(True).alias("is_literal"))
        pieces.append(own if literal_scope == "occurrence" else own.dropDuplicates(["node_id"]))
    nodes = _union(pieces).join(F.broadcast(types.select("type_id", "type_name")), "type_name")
    return KnowledgeGraph(nodes.select("node_id", "node_key", "type_id", "text", tokenize(F.col("text"), spec.prose).alias("tokens"), "is_literal"), links.distinct() if any(e.explode for e in spec.edges) else links, types, attrs, parts=_parts(spec, read, ident, attr_id, type_id, lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")) if literal_scope == "occurrence" else None)


def _parts(spec: GraphSpec, read: Callable[[str], DataFrame], ident: Callable[[str, str], Column], attr_id: dict[str, int], type_id: dict[str, int], stored: Callable[[str], DataFrame]) -> tuple[list[NodePart], list[EdgePart]] | None:
    """The rules' nodes and edges one by one; None where a rule's nodes have several types or edges of several rows are one."""
    if any(n.type_expr is not None for n in spec.nodes) or any(e.explode for e in spec.edges):
        return None
    words = lambda text: tokenize(text, spec.prose)
    nodes, edges, place = [], [], {}
    place_of = {n.kind: i + 1 for i, n in enumerate(spec.nodes)}

    def plain(table: str, key: str) -> DataFrame | None:
        made = spec.placed.get((table, key))
        return None if made is None else stored(table).where(f"{made} IS NOT NULL")

    def placed(table: str, key: str, digits: bool) -> dict:
        rows, made = plain(table, key), spec.placed.get((table, key))
        return {} if rows is None else {"plain": rows, "unkeyed": stored(table).where(f"{made} IS NULL"), "plain_keys": row_keys(rows, made) if digits else None}

    def open_ended(table: str, src_key: str, dst_key: str, src: Column, dst: Column) -> dict:
        at_src, at_dst = plain(table, src_key), plain(table, dst_key)
        if at_src is None and at_dst is None:
            return {}
        none, end = F.lit(None).cast("bigint"), src if at_src is None else dst
        rows = (at_dst if at_src is None else at_src).select((end if at_src is None else none).alias("src"), (none if at_src is None else end).alias("dst"))
        return {"plain": rows, "plain_end": end}

    def at_value(table: str, key: str, rule: Callable[[DataFrame], DataFrame]) -> dict:
        """``rule`` on the rows of one made value alone: the filter passes below the window that makes the keys."""
        made = spec.placed.get((table, key))
        return {} if made is None else {"at": lambda value: rule(read(table).where(F.col(made) == value))}

    def made_values(table: str, key: str, *more: Column) -> dict:
        rows = plain(table, key)
        return {} if rows is None else {"made": rows.select(F.col(spec.placed[table, key]).cast("bigint").alias("made"), *more)}

    def stored_rows(kind: str, table: str, key: str) -> dict:
        return {} if table in spec.derived else {"table": stored(table).where(f"{key} IS NOT NULL"), "ident": ident(kind, key)}

    def key_rows(table: str, key: str) -> dict:
        return {"keys": read(table).select(F.expr(f"CAST({key} AS BIGINT)").alias("key")), "keyed_by": (table, key)}

    def sources(e: EdgeRule, ends: DataFrame) -> DataFrame:
        met = ends.select("node_id", F.lit(True).alias("met"))
        mark = lambda t: t.join(met, ident(e.dst, e.dst_key) == met["node_id"], "left").withColumn("held", F.coalesce("met", F.lit(False)))
        return keys_where(stored(e.table), spec.placed[e.table, e.src_key], e.src_key, mark).select(ident(e.src, e.src_key).alias("id"))

    for n in spec.nodes:
        rule = lambda t, n=n: t.where(f"{n.key} IS NOT NULL").select(ident(n.kind, n.key).alias("node_id"), F.expr(n.text).alias("text"))
        rows = rule(read(n.table))
        own = {"code": place_of[n.kind]} | made_values(n.table, n.key) | at_value(n.table, n.key, rule) if (n.table, n.key) in spec.unique else {}
        place[n.kind] = len(nodes)
        nodes.append(NodePart(type_id[n.kind], rows, read(n.table).select(F.expr(n.text).alias("text")), words, (n.table, n.key) in spec.unique, n.text == f"CAST({n.key} AS STRING)", (n.table, n.key), **key_rows(n.table, n.key), **stored_rows(n.kind, n.table, n.key), text=F.expr(n.text), **placed(n.table, n.key, n.text == f"CAST({n.key} AS STRING)"), **own))
    for e in spec.edges:
        rule = lambda t, e=e: t.where(f"{e.src_key} IS NOT NULL AND {e.dst_key} IS NOT NULL").select(ident(e.src, e.src_key).alias("src"), ident(e.dst, e.dst_key).alias("dst"))
        rows, own = rule(read(e.table)), at_value(e.table, e.src_key, rule)
        if own and (e.table, e.dst_key) not in spec.placed:
            own |= made_values(e.table, e.src_key, ident(e.dst, e.dst_key).alias("dst")) | {"sources": lambda ends, e=e: sources(e, ends)}
        edges.append(EdgePart(attr_id[e.attr], place[e.src], place[e.dst], rows, (e.table, e.src_key), (e.table, e.dst_key), **open_ended(e.table, e.src_key, e.dst_key, ident(e.src, e.src_key), ident(e.dst, e.dst_key)), **own, src_ident=ident(e.src, e.src_key), dst_ident=ident(e.dst, e.dst_key)))
    for x in spec.literals:
        value = F.expr(f"CAST({x.value} AS STRING)")
        held = read(x.table).where(f"{x.src_key} IS NOT NULL").select(ident(x.src, x.src_key).alias("src"), value.alias("text")).where("text IS NOT NULL")
        node = -(F.col("src") * ATTRS + F.lit(attr_id[x.attr]))
        edges.append(EdgePart(attr_id[x.attr], place[x.src], len(nodes), held.select("src", node.alias("dst")), (x.table, x.src_key), (x.attr, "literal"), **open_ended(x.table, x.src_key, "", F.lit(None).cast("bigint"), value), src_ident=ident(x.src, x.src_key), dst_ident=value))
        row = plain(x.table, x.src_key)
        # a literal of a row that is a node by itself is as unique as that node
        nodes.append(NodePart(type_id[LITERAL_TYPE], held.select(node.alias("node_id"), "text"), read(x.table).select(value.alias("text")).distinct(), words, (x.table, x.src_key) in spec.unique, source=(x.attr, "literal"), **key_rows(x.table, x.src_key), **({} if row is None else placed(x.table, x.src_key, False) | {"plain": row.select(value.alias("text")).where("text IS NOT NULL")})))
    return nodes, edges


def graph_from_triples(triples: DataFrame, types_of: DataFrame, texts_of: DataFrame | None = None) -> KnowledgeGraph:
    """Graph of ``triples(subject, attr, object)``; subjects and typed objects are entities, other objects plain text.

    ``types_of(entity, type_name)`` and ``texts_of(entity, text)`` describe entities; an entity without text is described
    by its name. Equal triples count once.
    """
    spark = triples.sparkSession
    t = triples.where("subject IS NOT NULL AND attr IS NOT NULL AND object IS NOT NULL").distinct()
    types = schema_table(spark, [LITERAL_TYPE, *(n for n in schema_names(types_of.select("type_name")) if n != LITERAL_TYPE)], "type")
    attrs = schema_table(spark, schema_names(t.select("attr")), "attr")
    texts = (texts_of or types_of.select("entity", F.col("entity").alias("text"))).dropDuplicates(["entity"])
    ent = types_of.dropDuplicates(["entity"]).join(F.broadcast(types.select("type_id", "type_name")), "type_name").join(texts, "entity", "left")
    entities = ent.select(F.xxhash64("entity").alias("node_id"), F.col("entity").alias("node_key"), "type_id", F.coalesce("text", "entity").alias("text"), F.lit(False).alias("is_literal"))
    named = t.join(F.broadcast(attrs.select("attr_id", F.col("attr_name").alias("attr"))), "attr").join(types_of.select(F.col("entity").alias("object"), F.lit(True).alias("typed")).dropDuplicates(["object"]), "object", "left")
    literal = F.xxhash64("subject", "attr", "object")
    edges = named.select(F.xxhash64("subject").alias("src"), "attr_id", F.when(F.col("typed"), F.xxhash64("object")).otherwise(literal).alias("dst"))
    dummies = named.where("typed IS NULL").select(literal.alias("node_id"), F.concat_ws(".", "subject", "attr", "object").alias("node_key"), F.lit(0).alias("type_id"), F.col("object").alias("text"), F.lit(True).alias("is_literal"))
    nodes = entities.unionByName(dummies)
    return KnowledgeGraph(nodes.select("node_id", "node_key", "type_id", "text", tokenize(F.col("text")).alias("tokens"), "is_literal"), edges, types, attrs)


def id_collisions(graph: KnowledgeGraph) -> DataFrame:
    """Node ids that stand for more than one key: empty for a sound graph."""
    return graph.nodes.groupBy("node_id").agg(F.countDistinct("node_key").alias("keys")).where("keys > 1")


def induced_subgraph(graph: KnowledgeGraph, fraction: float, seed: int = 0, by: str = "entity") -> KnowledgeGraph:
    """The graph on a sample of entities or of types, with the edges among what is kept; literals follow their edges' sources."""
    from ..functions.patterns import root_sample

    key = F.col("node_id") if by == "entity" else F.col("type_id")
    chosen = root_sample(key, seed, F.lit(fraction))
    kept = graph.nodes.where(F.col("is_literal") | chosen)
    entities = kept.where(~F.col("is_literal")).select("node_id")
    edges = graph.edges.join(entities.withColumnRenamed("node_id", "src"), "src", "left_semi")
    edges = edges.join(kept.select(F.col("node_id").alias("dst")), "dst", "left_semi").select("src", "attr_id", "dst")
    nodes = kept.where(~F.col("is_literal")).unionByName(kept.where("is_literal").join(edges.select(F.col("dst").alias("node_id")).distinct(), "node_id", "left_semi").select(kept.columns))
    return KnowledgeGraph(nodes, edges, graph.types, graph.attrs)
