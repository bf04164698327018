"""Search methods: ranked tree patterns for a set of words.

All methods join postings of the words on their common root. They differ in what they do first: enumerate everything
(baseline), try combinations of path patterns, intersect roots, or work type by type with sampled roots.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.patterns import edges_of, height, is_tree, root_sample
from ..functions.scoring import ScoreSpec, order_key
from ..sources.graph import KnowledgeGraph
from .index import PathIndex, pattern_dictionary, schema_words, text_words
from .lineage import store
from .walk import Walk, walked_index

VALIDITY = ("tree", "product")
#: Chosen patterns (k for each root type) are broadcast up to this many rows.
CHOSEN_ROWS = 200_000


@dataclass(frozen=True)
class Query:
    """Words in order without repeats, and how subtrees are judged."""

    words: tuple[str, ...]
    score: ScoreSpec = field(default_factory=ScoreSpec)
    validity: str = "tree"
    #: Order in which postings are joined (default: as given); results keep the words' own order.
    order: tuple[str, ...] = ()

    def __post_init__(self) -> None:
        if self.validity not in VALIDITY:
            raise ValueError(f"unknown validity {self.validity!r}")
        if not self.words:
            raise ValueError("a query needs a word")
        object.__setattr__(self, "words", tuple(dict.fromkeys(self.words)))

    @property
    def ids(self) -> list[str]:
        return [f"p{i}" for i in range(1, len(self.words) + 1)]


def _frames(postings: DataFrame, q: Query, arrays: bool) -> list[DataFrame]:
    """Each word's postings as ``root, root_type, p<i>, edges<i>, <column><i>``."""
    out = []
    for i, w in enumerate(q.words, 1):
        cols = ["root", "root_type", F.col("pattern_id").alias(f"p{i}"), *(F.col(c).alias(f"{c}{i}") for c in q.score.columns)]
        if arrays:
            cols += [F.col("nodes").alias(f"nodes{i}"), F.col("attrs").alias(f"attrs{i}")]
        out.append(postings.where(F.col("word") == w).select(*cols))
    return out


def candidate_roots(postings: DataFrame, q: Query) -> DataFrame:
    """``root, root_type`` of every root that reaches all words."""
    one = lambda w: postings.where(F.col("word") == w).select("root", "root_type").distinct()
    return reduce(lambda a, w: a.join(one(w), ["root", "root_type"], "left_semi"), q.words[1:], one(q.words[0]))


def tree_check_needed(index: PathIndex) -> bool:
    """Whether two paths from one root can meet: only then must subtrees be checked. Found once for an index.

    Derived from the schema and the data: safe if every attribute has one value at most for each entity, no value is
    shared, and no root type reaches a type (other than unshared text) by two label paths.
    """
    if "check" not in index.facts:
        index.facts["check"] = _paths_can_meet(index)
    return index.facts["check"]


def _paths_can_meet(index: PathIndex) -> bool:
    g = index.graph
    if g.edges.groupBy("src", "attr_id").count().where("count > 1").limit(1).count():
        return True
    literal_shared = g.nodes.where("is_literal").join(g.edges, F.col("node_id") == F.col("dst")).groupBy("node_id").count().where("count > 1").limit(1).count() > 0
    ends = index.patterns.where(~F.col("ends_on_edge")).select("root_type", "labels", F.try_element_at("labels", F.lit(-1)).alias("last"))
    if not literal_shared:
        ends = ends.where("last <> 0")
    return ends.groupBy("root_type", "last").agg(F.count_distinct("labels").alias("n")).where("n > 1").limit(1).count() > 0


def must_check(index: PathIndex, q: Query, check: bool | None) -> bool:
    """``check`` as given; None asks for the check only where subtrees have to be trees and paths of this index can meet."""
    return q.validity == "tree" and tree_check_needed(index) if check is None else check


def join_trees(postings: DataFrame, q: Query, keep_paths: bool = False, check: bool | None = None) -> DataFrame:
    """One row for each valid subtree: ``root, root_type, p1.., tree_score``, with the paths if wanted.

    Paths are joined word by word on the root; under tree validity a combination that is no tree is dropped as soon as two
    of its paths meet, so dead prefixes do not multiply.
    """
    check = q.validity == "tree" if check is None else check
    arrays = check or keep_paths
    frames = _frames(postings, q, arrays)
    if check:
        frames = [f.withColumn(f"edges{i}", edges_of(F.col(f"nodes{i}"), F.col(f"attrs{i}"))) for i, f in enumerate(frames, 1)]
        if not keep_paths:
            frames = [f.drop(f"nodes{i}", f"attrs{i}") for i, f in enumerate(frames, 1)]
    turn = [q.words.index(w) for w in q.order] if q.order else list(range(len(q.words)))
    acc = frames[turn[0]]
    for n, i in enumerate(turn[1:], 2):
        acc = acc.join(frames[i], ["root", "root_type"])
        if check:
            acc = acc.where(is_tree([F.col(f"edges{j + 1}") for j in turn[:n]]))
    m = len(q.words)
    for c in q.score.columns:
        acc = acc.withColumn(c, sum((F.col(f"{c}{i}") for i in range(2, m + 1)), F.col(f"{c}1")))
    out = acc.withColumn("tree_score", q.score.tree_score())
    paths = [x for i in range(1, m + 1) for x in (f"nodes{i}", f"attrs{i}")] if keep_paths else []
    return out.select("root", "root_type", *q.ids, *q.score.columns, "tree_score", *paths)


def group_trees(trees: DataFrame, q: Query, scale: Column | None = None) -> DataFrame:
    """``root_type, p1.., n_trees, score`` of every pattern that has a subtree."""
    return trees.groupBy("root_type", *q.ids).agg(F.count(F.lit(1)).alias("n_trees"), q.score.pattern_score(scale).alias("score"))


def _order(q: Query, score: str = "score") -> list[Column]:
    """Best first; equal scores by pattern ids, which follow the label texts."""
    return [order_key(score).desc(), *map(F.asc, q.ids)]


def rank_patterns(grouped: DataFrame, q: Query, patterns: DataFrame, k: int | None) -> DataFrame:
    """``rank, pattern_ids, label, height, n_trees, score``: the k best (None: all), labelled.

    With k the driver-side sort holds k rows, and those are broadcast to the dictionary, whatever its size; all patterns are
    labelled by joins that the planner chooses.
    """
    top = grouped.orderBy(*_order(q)).limit(k) if k is not None else grouped
    names = patterns.select("pattern_id", F.col("label").alias("text"), F.col("len").alias("nodes"))
    few = F.broadcast if k is not None and k <= CHOSEN_ROWS else (lambda x: x)
    out = top
    for i, p in enumerate(q.ids, 1):
        own = names.select(F.col("pattern_id").alias(p), F.col("text").alias(f"label{i}"), F.col("nodes").alias(f"nodes{i}"))
        out = own.join(few(out), p)
    ranked = out.withColumn("rank", F.row_number().over(Window.orderBy(*_order(q)))) if k is not None else out.withColumn("rank", F.lit(None).cast("int"))
    extra = [c for c in ("score_est",) if c in grouped.columns]
    return ranked.select("rank", F.array(*q.ids).alias("pattern_ids"), F.concat_ws(" | ", *(f"label{i}" for i in range(1, len(q.ids) + 1))).alias("label"), height([F.col(f"nodes{i}") for i in range(1, len(q.ids) + 1)]).alias("height"), "n_trees", "score", *extra)


# -- baseline


def backward_postings(graph: KnowledgeGraph, q: Query, d: int, nearest_match_only: bool = False) -> tuple[DataFrame, DataFrame]:
    """(postings, patterns) of the words by walking edges backward from their matches, without an index.

    ``nearest_match_only`` stops at an entity that holds the word itself: paths never pass through another match. A graph
    with parts is walked table by table, and only roots that reach every word keep their paths.
    """
    if graph.parts is not None and graph.ranks is None and not nearest_match_only:
        index = walked_index(graph, d)
        return Walk(index, q.words, whole=False).rooted(), index.patterns
    chosen = F.col("word").isin(list(q.words))
    nodes = graph.ranked_nodes()
    types = F.broadcast(schema_words(graph.types, "type_id").where(chosen))
    hits = text_words(graph).where(chosen).unionByName(nodes.select("node_id", "type_id").join(types, "type_id").select("word", "node_id", "sim")).groupBy("word", "node_id").agg(F.max("sim").alias("sim"))
    start = hits.join(nodes, "node_id").select("word", F.col("node_id").alias("head"), F.array("node_id").alias("nodes"), F.array().cast("array<int>").alias("attrs"), F.array("type_id").alias("labels"), F.lit(1).alias("len"), "pr", "sim", F.lit(False).alias("ends_on_edge"))
    attrs = F.broadcast(schema_words(graph.attrs, "attr_id").where(chosen))
    src = nodes.select(F.col("node_id").alias("src"), F.col("type_id").alias("src_type"), F.col("pr").alias("src_pr"))
    dst = nodes.select(F.col("node_id").alias("dst"), F.col("type_id").alias("dst_type"))
    steps = graph.edges.join(src, "src").select("src", "attr_id", "dst", "src_type", "src_pr")
    on_edge = steps.join(attrs, "attr_id").where("src <> dst").join(dst, "dst").select("word", F.col("src").alias("head"), F.array("src", "dst").alias("nodes"), F.array("attr_id").alias("attrs"), F.array("src_type", "attr_id", "dst_type").alias("labels"), F.lit(2).alias("len"), F.col("src_pr").alias("pr"), "sim", F.lit(True).alias("ends_on_edge"))
    level, out = start, None
    for n in range(1, d + 1):
        if n == 2:
            level = level.unionByName(on_edge)
        out = level if out is None else out.unionByName(level)
        if n == d:
            break
        walk = level
        if nearest_match_only:
            # nothing beyond a match, but for the match at the path's own end
            held = hits.select(F.col("word").alias("hit_word"), F.col("node_id").alias("hit"))
            inner = (F.col("len") > 1) & (F.col("word") == F.col("hit_word")) & (F.col("head") == F.col("hit"))
            walk = level.join(held, inner, "left_anti")
        level = walk.join(steps, walk["head"] == steps["dst"]).where(~F.array_contains("nodes", F.col("src"))).select("word", F.col("src").alias("head"), F.concat(F.array("src"), "nodes").alias("nodes"), F.concat(F.array("attr_id"), "attrs").alias("attrs"), F.concat(F.array("src_type", "attr_id"), "labels").alias("labels"), F.lit(n + 1).alias("len"), "pr", "sim", "ends_on_edge")
    out = out.withColumn("labels", F.when(F.col("ends_on_edge"), F.slice("labels", F.lit(1), F.size("labels") - 1)).otherwise(F.col("labels")))
    patterns = pattern_dictionary_of(out, graph)
    ids = F.broadcast(patterns.select("labels", "ends_on_edge", "pattern_id"))
    return out.join(ids, ["labels", "ends_on_edge"]).select("word", "pattern_id", F.col("head").alias("root"), F.col("labels")[0].alias("root_type"), "nodes", "attrs", "len", "pr", "sim"), patterns


def pattern_dictionary_of(matches: DataFrame, graph: KnowledgeGraph) -> DataFrame:
    """Dictionary of the patterns of matches, whose labels are already cut for edge matches."""
    full = F.when(F.col("ends_on_edge"), F.concat("labels", F.array(F.lit(0)))).otherwise(F.col("labels"))
    every = pattern_dictionary(matches.select(full.alias("labels")), graph)
    return every.join(F.broadcast(matches.select("labels", "ends_on_edge").distinct()), ["labels", "ends_on_edge"], "left_semi")


def enumerate_then_group(graph: KnowledgeGraph, q: Query, d: int, k: int | None = 100, nearest_match_only: bool = False) -> DataFrame:
    """Baseline: all subtrees by backward expansion, then one grouping by pattern."""
    postings, patterns = backward_postings(graph, q, d, nearest_match_only)
    return rank_patterns(group_trees(join_trees(postings, q), q), q, patterns, k)


# -- combinations of path patterns


def pattern_candidates(postings: DataFrame, q: Query) -> DataFrame:
    """``root_type, p1..``: every combination of the words' path patterns with one root type."""
    lists = [postings.where(F.col("word") == w).select("root_type", F.col("pattern_id").alias(p)).distinct() for w, p in zip(q.words, q.ids, strict=True)]
    return reduce(lambda a, b: a.join(b, "root_type"), lists)


def _combine(postings: DataFrame, q: Query, lists: list[DataFrame], prune: str) -> DataFrame:
    """The words' ``lists`` (a row for each root and pattern) joined to the roots of every combination."""
    if prune == "prefix":
        return reduce(lambda a, b: a.join(b, ["root", "root_type"]), lists)
    out = pattern_candidates(postings, q).join(lists[0], ["root_type", q.ids[0]])
    for p, rows in zip(q.ids[1:], lists[1:], strict=True):
        out = out.join(rows, ["root", "root_type", p])
    return out


def nonempty_roots(postings: DataFrame, q: Query, prune: str = "prefix") -> DataFrame:
    """``root, root_type, p1..``: the roots of every combination whose root lists intersect.

    ``prefix`` intersects list by list and drops a combination at its first empty prefix; ``none`` forms every combination
    and tests each against all of its lists.
    """
    lists = [postings.where(F.col("word") == w).select("root", "root_type", F.col("pattern_id").alias(p)).distinct() for w, p in zip(q.words, q.ids, strict=True)]
    return _combine(postings, q, lists, prune).select("root", "root_type", *q.ids)


def pattern_product(index: PathIndex, q: Query, k: int | None = 100, prune: str = "prefix", check: bool | None = None) -> DataFrame:
    """Combinations with common roots first, scored pattern by pattern; k patterns are kept.

    Where no combination of paths has to be checked, the root lists carry each word's sums and a combination is scored as soon
    as its lists are intersected; otherwise the paths of what is left are joined.
    """
    postings = index.scan(list(q.words))
    check = must_check(index, q, check)
    if not check and has_closed_form(q):
        grouped = closed_scores(_combine(postings, q, root_sums(postings, q), prune), q)
        return rank_patterns(grouped.withColumn("n_trees", F.col("n_trees").cast("bigint")), q, index.patterns, k)
    acc = nonempty_roots(postings, q, prune)
    for i, f in enumerate(_frames(postings, q, check), 1):
        f = f.withColumn(f"edges{i}", edges_of(F.col(f"nodes{i}"), F.col(f"attrs{i}"))).drop(f"nodes{i}", f"attrs{i}") if check else f
        acc = acc.join(f, ["root", "root_type", f"p{i}"])
        if check and i > 1:
            acc = acc.where(is_tree([F.col(f"edges{j}") for j in range(1, i + 1)]))
    m = len(q.words)
    for c in q.score.columns:
        acc = acc.withColumn(c, sum((F.col(f"{c}{i}") for i in range(2, m + 1)), F.col(f"{c}1")))
    grouped = group_trees(acc.withColumn("tree_score", q.score.tree_score()), q)
    return rank_patterns(grouped, q, index.patterns, k)


def emptiness_counters(index: PathIndex, q: Query) -> DataFrame:
    """``tried, nonempty, empty, intersections, pruned_intersections``: what the pattern product spends on empty combinations.

    Without pruning every combination intersects all its lists; with it, one intersection for each prefix that is reached.
    """
    postings = index.postings(list(q.words))
    tried = pattern_candidates(postings, q).agg(F.count(F.lit(1)).alias("tried"))
    full = nonempty_roots(postings, q).select(*q.ids).distinct().agg(F.count(F.lit(1)).alias("nonempty"))
    reached = None
    for n in range(2, len(q.words) + 1):
        part = Query(q.words[: n - 1], q.score, q.validity)
        alive = nonempty_roots(postings, part).select("root_type", *part.ids).distinct()
        nxt = postings.where(F.col("word") == q.words[n - 1]).select("root_type", F.col("pattern_id").alias(f"p{n}")).distinct()
        step = alive.join(nxt, "root_type").agg(F.count(F.lit(1)).alias("n"))
        reached = step if reached is None else reached.unionByName(step)
    pruned = reached.agg(F.sum("n").alias("pruned_intersections")) if reached is not None else tried.select(F.lit(0).cast("bigint").alias("pruned_intersections"))
    return tried.crossJoin(full).crossJoin(pruned).select("tried", "nonempty", (F.col("tried") - F.col("nonempty")).alias("empty"), (F.col("tried") * (len(q.words) - 1)).alias("intersections"), "pruned_intersections")


# -- roots first


def root_expansion(index: PathIndex, q: Query, k: int | None = None, level: str = "scores", return_trees: bool = False, check: bool | None = None, pattern_ids: list[int] | None = None) -> DataFrame:
    """Common roots first, then every subtree under them, grouped by pattern. ``level="patterns"`` stops at patterns with a common root.

    ``pattern_ids`` asks for one tree pattern: each word's paths of other patterns are left out before roots are compared.
    """
    postings = index.scan(list(q.words))
    if pattern_ids is not None:
        own = [(F.col("word") == w) & (F.col("pattern_id") == int(p)) for w, p in zip(q.words, pattern_ids, strict=True)]
        postings = postings.where(reduce(lambda a, b: a | b, own))
    if level == "patterns":
        return nonempty_roots(postings, q).select("root_type", *q.ids).distinct()
    roots = candidate_roots(postings, q) if len(q.words) > 1 else None
    held = postings.join(roots, ["root", "root_type"], "left_semi") if roots is not None else postings
    trees = join_trees(held, q, keep_paths=return_trees, check=must_check(index, q, check))
    return trees if return_trees else rank_patterns(group_trees(trees, q), q, index.patterns, k)


def root_path_counts(postings: DataFrame, q: Query) -> DataFrame:
    """``root, root_type, n``: combinations of paths under each common root, counted without forming them."""
    counts = [postings.where(F.col("word") == w).groupBy("root", "root_type").agg(F.count(F.lit(1)).cast("decimal(38,0)").alias(f"n{i}")) for i, w in enumerate(q.words)]
    joined = reduce(lambda a, b: a.join(b, ["root", "root_type"]), counts)
    # doubles are exact to 2^53 and cannot overflow
    return joined.select("root", "root_type", reduce(lambda a, b: a * b, [F.col(f"n{i}").cast("double") for i in range(len(q.words))]).alias("n"))


def subtree_counts(index: PathIndex, q: Query, by: str | None = "root_type") -> DataFrame:
    """Path combinations (an upper bound of subtrees, exact for product validity) by root type or in all."""
    counted = index.path_counts(list(q.words))
    if counted is not None:
        numbers = [F.col(f"n{i}") for i in range(len(q.words))]
        per_root = counted.where(reduce(lambda a, b: a & b, [n > 0 for n in numbers])).select("root_type", "m", (reduce(lambda a, b: a * b, [n.cast("double") for n in numbers]) * F.col("m")).alias("n"))
        total = [F.coalesce(F.sum("m"), F.lit(0)).alias("roots")]
    else:
        per_root = root_path_counts(index.scan(list(q.words)), q)
        total = [F.count(F.lit(1)).alias("roots")]
    total.append(F.coalesce(F.sum("n"), F.lit(0.0)).alias("n_trees"))
    return per_root.groupBy("root_type").agg(*total) if by == "root_type" else per_root.agg(*total)


def count_patterns(index: PathIndex, q: Query) -> DataFrame:
    """``n_patterns``: by enumeration, as no shortcut exists."""
    trees = root_expansion(index, q, return_trees=True) if q.validity == "tree" else nonempty_roots(index.scan(list(q.words)), q)
    return trees.select(*q.ids).distinct().agg(F.count(F.lit(1)).alias("n_patterns"))


def state_size(index: PathIndex, q: Query) -> DataFrame:
    """``whole, largest_type``: subtrees held at once by one dictionary for all types and by one for each type."""
    return subtree_counts(index, q).agg(F.coalesce(F.sum("n_trees"), F.lit(0.0)).alias("whole"), F.coalesce(F.max("n_trees"), F.lit(0.0)).alias("largest_type"))


# -- type by type


def typed_topk(index: PathIndex, q: Query, k: int | None = 100, lam: float = float("inf"), rho: float = 1.0, seed: int = 0, schedule: str = "single_pass", check: bool | None = None, batch_trees: float = 1e7) -> DataFrame:
    """The k best of each root type (None: all), then of all; types with ``lam`` or more path combinations are estimated from
    sampled roots.

    Roots are kept by a digest of their id, so a run repeats anywhere. Estimated leaders of sampled types are scored again
    over all roots. ``single_pass`` lets one spilling aggregation hold all types. ``loop`` runs one type after the other and
    keeps only its k patterns (written out) before the next begins, so the state is that of the largest type; ``batches``
    runs types together as long as they have ``batch_trees`` path combinations or fewer.
    """
    if k is None and rho < 1.0 and lam != float("inf"):
        raise ValueError("sampling needs k: only leaders are scored again")
    postings = index.scan(list(q.words))
    if schedule in ("loop", "batches"):
        sizes = subtree_counts(index, q).orderBy("root_type").collect()  # a row for each root type
        lots: list[list[int]] = []
        held = 0.0
        for r in sizes:
            if schedule == "batches" and lots and held + r["n_trees"] <= batch_trees:
                lots[-1].append(r["root_type"])
                held += r["n_trees"]
            else:
                lots.append([r["root_type"]])
                held = r["n_trees"]
        parts = [store(_typed(index, postings.where(F.col("root_type").isin(lot)), q, k, lam, rho, seed, check)) for lot in lots]
        grouped = reduce(DataFrame.unionByName, parts) if parts else _typed(index, postings, q, k, lam, rho, seed, check)
    elif schedule == "single_pass":
        grouped = _typed(index, postings, q, k, lam, rho, seed, check)
    else:
        raise ValueError(f"unknown schedule {schedule!r}")
    return rank_patterns(grouped, q, index.patterns, k)


def _typed(index: PathIndex, postings: DataFrame, q: Query, k: int | None, lam: float, rho: float, seed: int, check: bool | None) -> DataFrame:
    best = Window.partitionBy("root_type").orderBy(order_key("score").desc(), *map(F.asc, q.ids))
    check = must_check(index, q, check)

    def of(roots: DataFrame) -> DataFrame:
        return group_trees(join_trees(postings.join(roots, ["root", "root_type"], "left_semi"), q, check=check), q)

    def leading(grouped: DataFrame) -> DataFrame:
        return grouped if k is None else grouped.withColumn("place", F.row_number().over(best)).where(F.col("place") <= k).drop("place")

    if lam == float("inf") or rho >= 1.0:
        return leading(of(candidate_roots(postings, q))).withColumn("score_est", F.col("score"))
    # common roots with their path combinations: read once from the postings, then twice from a table of roots
    roots = store(root_path_counts(postings, q))
    heavy = [r["root_type"] for r in roots.groupBy("root_type").agg(F.sum("n").alias("n")).where(F.col("n") >= lam).select("root_type").collect()]  # types: the schema's size
    if not heavy:
        return leading(of(roots)).withColumn("score_est", F.col("score"))
    is_heavy = F.col("root_type").isin(heavy)
    rate = F.when(is_heavy, F.lit(rho)).otherwise(F.lit(1.0))
    grouped = of(roots.where(root_sample(F.col("root"), seed, rate)))
    scaled = grouped.withColumn("score", F.col("score") / rate) if q.score.agg in ("sum", "count") else grouped
    leaders = store(leading(scaled).withColumnRenamed("score", "score_est"))
    light = leaders.where(~is_heavy).withColumn("score", F.col("score_est"))  # not sampled, so exact already
    small = F.broadcast if k * len(heavy) <= CHOSEN_ROWS else (lambda x: x)
    chosen = leaders.where(is_heavy).select("root_type", *q.ids, "score_est")
    exact = _rescored(postings.where(is_heavy), q, chosen, small, check).join(small(chosen), ["root_type", *q.ids])
    return exact.unionByName(light)


def _rescored(postings: DataFrame, q: Query, chosen: DataFrame, small, check: bool) -> DataFrame:
    """``root_type, p1.., n_trees, score`` of chosen patterns (root_type, p1..) over all roots: from sums for each root where
    no subtree has to be checked, else from the subtrees. Every prefix that no chosen pattern has is dropped at once."""
    closed = not check and has_closed_form(q)
    acc = None
    for i, f in enumerate(root_sums(postings, q) if closed else _frames(postings, q, check), 1):
        f = f.join(small(chosen.select("root_type", f"p{i}").distinct()), ["root_type", f"p{i}"], "left_semi")
        f = f.withColumn(f"edges{i}", edges_of(F.col(f"nodes{i}"), F.col(f"attrs{i}"))).drop(f"nodes{i}", f"attrs{i}") if check else f
        if acc is None:
            acc = f
            continue
        acc = acc.join(f, ["root", "root_type"]).join(small(chosen.select("root_type", *q.ids[:i]).distinct()), ["root_type", *q.ids[:i]], "left_semi")
        if check:
            acc = acc.where(is_tree([F.col(f"edges{j}") for j in range(1, i + 1)]))
    if closed:
        return closed_scores(acc, q).withColumn("n_trees", F.col("n_trees").cast("bigint"))
    for c in q.score.columns:
        acc = acc.withColumn(c, sum((F.col(f"{c}{i}") for i in range(2, len(q.words) + 1)), F.col(f"{c}1")))
    return group_trees(acc.withColumn("tree_score", q.score.tree_score()), q)


# -- single subtrees, decompositions


def individual_topk(index: PathIndex, q: Query, k: int = 100) -> DataFrame:
    """``rank, root, pattern_ids, tree_score`` of the k best single subtrees, with their paths."""
    trees = root_expansion(index, q, return_trees=True)
    order = [order_key("tree_score").desc(), *map(F.asc, q.ids), F.asc("root"), *(F.asc(f"nodes{i}") for i in range(1, len(q.words) + 1))]
    top = trees.orderBy(*order).limit(k)
    paths = [x for i in range(1, len(q.words) + 1) for x in (f"nodes{i}", f"attrs{i}")]
    return top.withColumn("rank", F.row_number().over(Window.orderBy(*order))).select("rank", "root", F.array(*q.ids).alias("pattern_ids"), "tree_score", *paths)


def score_by_root(index: PathIndex, q: Query) -> DataFrame:
    """``root, p1.., n_trees, score``: what each root adds to each pattern's sum."""
    trees = root_expansion(index, q, return_trees=True)
    return trees.groupBy("root", *q.ids).agg(F.count(F.lit(1)).alias("n_trees"), F.sum("tree_score").alias("score"))


def has_closed_form(q: Query) -> bool:
    """Whether a pattern's score follows from sums for each root: the three usual factors with exponents -1, 1, 1, no maximum."""
    return [(t.column, t.exponent) for t in q.score.terms] == [("len", -1.0), ("pr", 1.0), ("sim", 1.0)] and q.score.agg in ("sum", "avg", "count")


def root_sums(postings: DataFrame, q: Query) -> list[DataFrame]:
    """Each word's paths by root and pattern: their count, length, sums of ranks and similarities, and sum of the products."""
    sums = [F.count(F.lit(1)).cast("double").alias("n"), F.first("len").alias("l"), F.sum("pr").alias("a"), F.sum("sim").alias("b"), F.sum(F.col("pr") * F.col("sim")).alias("c")]
    by_word = [postings.where(F.col("word") == w).groupBy("root", "root_type", F.col("pattern_id").alias(p)).agg(*sums) for w, p in zip(q.words, q.ids, strict=True)]
    return [f.withColumnsRenamed({c: f"{c}{i}" for c in "nlabc"}) for i, f in enumerate(by_word, 1)]


def closed_scores(joined: DataFrame, q: Query) -> DataFrame:
    """``root_type, p1.., n_trees, score`` from the sums of all words at each common root.

    Under one root, a pattern's lengths are fixed, so the sum over all path combinations of (sum of ranks) times (sum of
    similarities) follows from each word's count, sums and sum of products.
    """
    m = len(q.words)
    others = lambda *skip: reduce(lambda a, b: a * b, [F.col(f"n{i}") for i in range(1, m + 1) if i not in skip], F.lit(1.0))
    total = reduce(lambda a, b: a + b, [F.col(f"c{i}") * others(i) for i in range(1, m + 1)] + [F.col(f"a{i}") * F.col(f"b{j}") * others(i, j) for i in range(1, m + 1) for j in range(1, m + 1) if i != j])
    size = reduce(lambda a, b: a + b, [F.col(f"l{i}") for i in range(1, m + 1)]).cast("double")
    n, s = F.sum(others()), F.sum(total / size)
    score = {"sum": s, "avg": s / n, "count": n}[q.score.agg]
    return joined.groupBy("root_type", *q.ids).agg(n.alias("n_trees"), score.alias("score"))


def factorised_scores(index: PathIndex, q: Query, k: int | None = None) -> DataFrame:
    """Pattern scores without forming subtrees, for product validity and scores with a closed form: work is in (root, pattern)
    pairs, not subtrees."""
    if not has_closed_form(q):
        raise ValueError("factorised scores need the three usual factors and sum, avg or count")
    joined = reduce(lambda a, b: a.join(b, ["root", "root_type"]), root_sums(index.scan(list(q.words)), q))
    return rank_patterns(closed_scores(joined, q), q, index.patterns, k)
