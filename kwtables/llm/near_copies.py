"""Near copies: SimHash finds the candidates, the exact Jaccard similarity of word shingles decides.

A text is the set of its lower-cased word shingles (64-bit hashes). Equal sets are one node from the start. Each node has a
few SimHash fingerprints; those within the radius in one of them are candidates, found by the generalised pigeonhole of
``simhash`` with its rows for each node bounded. A candidate becomes a link only if the whole sets have the similarity or
more, so no link is below it; a pair at the similarity itself is missed by all families only with a small chance.

No group is paired out. In each bucket a node reports the nearest of its earlier candidates (all, if there are no more than FEW), and
both sides of what it leaves out are marked as crowded. The nearest candidates are checked first and closed into
components; what remains to be checked are the reported pairs and the pairs of crowded nodes, found once more, that lie
across components, as far as their sizes and parity maps allow the similarity (two sets differ in as many members at least
as their maps differ in bits, so no similar pair is left out there).

Defined results: null or wordless texts are equal to each other and to nothing else; texts with fewer words than a shingle
are one shingle; the component is the least id reachable; ids must be integers (else TypeError); null ids cannot name a
component and are left out of it; an id that repeats with other texts is one document, linked by each of them; repeated rows
give repeated results; an empty table stays empty; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import broadcast_if, cut, join_hot, ship, trim
from .simhash import CHUNK_PAIRS, HOT_ROWS, HOT_SHARE, SEED, _majority, _mix, allocate_rows, bit_statistics, bits_for, components, deal, needs_integer_ids, whole_buckets

#: Fingerprints of each node, and stored and probed values of each of them at most (the bytes that a document moves).
FAMILIES, MOST_ROWS = 3, 40
#: Earlier candidates that a node reports from one bucket; of more it reports the nearest. At 1 a bucket of any size reports no more
#: rows than it has.
FEW = 1
#: Bits of a set's parity map, and of the short one that crowded nodes carry.
MAP_BITS, SHORT_BITS = 1_024, 256
SHORT = [f"m{i}" for i in range(SHORT_BITS // 64)]
#: Ids within this number are broadcast; beyond it they are joined by shuffle.
BROADCAST_IDS = 1_000_000
#: Distance of a row that only names a candidate.
NO_PAIR = 1 << 20


class _Hashes(dict):
    """Hashes of words; short words are remembered while they are few."""

    def __missing__(self, word: bytes) -> int:
        from xxhash import xxh64_intdigest

        h = xxh64_intdigest(word, SEED)
        if len(word) <= 32:
            if len(self) >= 100_000:
                self.clear()
            self[word] = h
        return h


_hashes = _Hashes()


def shingles(text: str | None, words: int) -> np.ndarray:
    """Sorted distinct hashes of a text's lower-cased word shingles."""
    tokens = (text or "").encode("utf-8", "replace").lower().split()
    if not tokens:
        return np.empty(0, dtype=np.int64)
    h = np.fromiter(map(_hashes.__getitem__, tokens), dtype=np.uint64, count=len(tokens))
    n = min(words, len(h))
    out = np.full(len(h) - n + 1, n, dtype=np.uint64)
    for i in range(n):
        out = (out ^ h[i : len(h) - n + 1 + i]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    return np.unique(out.view(np.int64))


def parity_map(members: np.ndarray, bits: int = MAP_BITS) -> bytes:
    n = np.bincount((members.view(np.uint64) % np.uint64(bits)).astype(np.int64), minlength=bits)
    return np.packbits((n & 1).astype(np.uint8)).tobytes()


def digest(members: np.ndarray) -> np.ndarray:
    return np.frombuffer(hashlib.blake2b(members.tobytes(), digest_size=16).digest(), dtype=np.int64)


def allowed(differ: np.ndarray, both: np.ndarray, similarity: Fraction) -> np.ndarray:
    """Whether sets of ``both`` members together that differ in ``differ`` or more can have the similarity."""
    num, den = similarity.numerator, similarity.denominator
    return differ * (den + num) <= (den - num) * both


def sketches(docs: DataFrame, words: int, families: int, id_col: str, text_col: str) -> DataFrame:
    """``id_col, d0, d1, n, map, f0, ..., m0, ...``: digest, size, parity map, fingerprints and short map of each row's set."""
    ship(docs.sparkSession)
    names = [*(f"f{i}" for i in range(families)), *SHORT]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            digests, sizes, maps, longs = [], [], [], []
            for t in batch.column(1):
                s = shingles(t.as_py(), words)
                digests.append(digest(s))
                sizes.append(len(s))
                maps.append(parity_map(s))
                prints = [_majority(_mix(s.view(np.uint64), i)) if len(s) else 0 for i in range(families)]
                longs.append(np.append(np.array(prints, dtype=np.uint64).view(np.int64), np.frombuffer(parity_map(s, SHORT_BITS), dtype=np.int64)))
            d = np.array(digests, dtype=np.int64).reshape(-1, 2)
            f = np.array(longs, dtype=np.int64).reshape(-1, len(names))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(d[:, 0]), pa.array(d[:, 1]), pa.array(sizes, pa.int32()), pa.array(maps, pa.binary()), *(pa.array(f[:, i]) for i in range(len(names)))], names=[id_col, "d0", "d1", "n", "map", *names])
        trim()

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, d0 bigint, d1 bigint, n int, map binary, " + ", ".join(f"{c} bigint" for c in names))


def close_pairs(data: np.ndarray, families: int, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row, later row, bits that differ in all families) of the pairs of one bucket within ``radius`` in some family, a bounded
    number of pairs at once; rows are (bucket, node, fingerprints, ...)."""
    bucket, f = data[:, 0] >> 1, np.ascontiguousarray(data[:, 2 : 2 + families]).view(np.uint64)
    last = np.flatnonzero(np.append(bucket[1:] != bucket[:-1], True))
    ends = np.repeat(last + 1, np.diff(np.append(-1, last)))
    first = np.flatnonzero(data[:, 0] & 1 == 0)  # stored values come before probes
    lens = ends[first] - first - 1
    first, lens = first[lens > 0], lens[lens > 0]
    reach, at = np.cumsum(lens), 0
    while at < len(first):
        stop = max(at + 1, int(np.searchsorted(reach, (reach[at - 1] if at else 0) + CHUNK_PAIRS, side="right")))
        i = np.repeat(first[at:stop], lens[at:stop])
        j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(lens[at:stop]) - lens[at:stop], lens[at:stop])
        near = np.bitwise_count(f[i, 0] ^ f[j, 0]) <= radius
        for c in range(1, families):
            near |= np.bitwise_count(f[i, c] ^ f[j, c]) <= radius
        i, j = i[near], j[near]
        yield i, j, np.bitwise_count(f[i] ^ f[j]).sum(axis=1, dtype=np.int64)
        at = stop


def reported(data: np.ndarray, families: int, radius: int) -> np.ndarray:
    """Rows (a, b, distance, crowded) of the candidates of whole buckets, FEW at most for each row of a bucket: b is the earlier
    node, or a itself in a mere mark; crowded says that candidates of a were left out or a as one."""
    found = [np.empty((0, 4), dtype=np.int64)]
    passed = [np.empty(0, dtype=np.int64)]
    for i, j, d in close_pairs(data, families, radius):
        x, y = data[i, 1], data[j, 1]
        pairs = np.stack([np.maximum(x, y), np.minimum(x, y), d, data[i, 0] >> 1], axis=1)[x != y]
        if not len(pairs):
            continue
        pairs = pairs[np.lexsort((pairs[:, 1], pairs[:, 2], pairs[:, 0], pairs[:, 3]))]
        new = np.append(True, (pairs[1:, 0] != pairs[:-1, 0]) | (pairs[1:, 3] != pairs[:-1, 3]))
        group = np.cumsum(new) - 1
        many = np.bincount(group)[group] > FEW
        pairs[:, 3] = many
        found.append(np.unique(pairs[new | ~many], axis=0))
        passed.append(np.unique(pairs[many, 1]))
    rows = np.unique(np.concatenate(found), axis=0)
    # of one pair the last row counts; earlier nodes of what is left out are crowded as well, with a row of their own if they have none
    rows = rows[np.append(np.any(rows[1:, :2] != rows[:-1, :2], axis=1), True)] if len(rows) else rows
    named = np.unique(np.concatenate(passed))
    rows[np.isin(rows[:, 0], named), 3] = 1
    named = np.setdiff1d(named, rows[:, 0])
    marks = np.stack([named, named, np.full(len(named), NO_PAIR), np.ones(len(named), dtype=np.int64)], axis=1)
    return np.concatenate([rows, marks])


def candidates(nodes: DataFrame, parts: list[tuple[str, list[int], int]], families: int, radius: int) -> DataFrame:
    """``a, b, distance, crowded`` of the nodes (node, f0, ...)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for data in whole_buckets(batches):
            rows = reported(data, families, radius)
            if len(rows):
                yield pa.RecordBatch.from_arrays([pa.array(rows[:, c]) for c in range(4)], names=["a", "b", "distance", "crowded"])
        trim()

    rows = deal(nodes, parts).mapInArrow(run, "a bigint, b bigint, distance bigint, crowded bigint")
    return rows.groupBy("a", "b").agg(F.min("distance").alias("distance"), F.max("crowded").alias("crowded"))


def crossing(crowded: DataFrame, parts: list[tuple[str, list[int], int]], families: int, radius: int, similarity: Fraction) -> DataFrame:
    """``a, b``: candidates among the crowded nodes (node, f0, ..., root, n, m0, ...) of different roots whose short maps allow the similarity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for data in whole_buckets(batches):
            found = [np.empty((0, 2), dtype=np.int64)]
            root, size = data[:, 2 + families], data[:, 3 + families]
            maps = np.ascontiguousarray(data[:, 4 + families :]).view(np.uint64)  # counts of signed numbers would be those of their absolute values
            for i, j, _ in close_pairs(data, families, radius):
                other = root[i] != root[j]
                i, j = i[other], j[other]
                fit = allowed(np.bitwise_count(maps[i] ^ maps[j]).sum(axis=1, dtype=np.int64), size[i] + size[j], similarity)
                x, y = data[i[fit], 1], data[j[fit], 1]
                found.append(np.unique(np.stack([np.maximum(x, y), np.minimum(x, y)], axis=1), axis=0))
            pairs = np.unique(np.concatenate(found), axis=0)
            if len(pairs):
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])
        trim()

    return deal(crowded, parts).mapInArrow(run, "a bigint, b bigint").distinct()


def possible(pairs: DataFrame, nodes: DataFrame, similarity: Fraction) -> DataFrame:
    """The ``pairs`` (a, b, ...) whose sizes and parity maps allow the similarity; no pair that has it is left out."""

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            both = batch.column(batch.num_columns - 3).to_numpy(zero_copy_only=False).astype(np.int64)
            x, y = (np.frombuffer(b"".join(batch.column(batch.num_columns - i).to_pylist()), dtype=np.uint8).reshape(len(both), MAP_BITS // 8) for i in (2, 1))
            fit = allowed(np.bitwise_count(x ^ y).sum(axis=1, dtype=np.int64), both, similarity)
            yield batch.select(list(range(batch.num_columns - 3))).filter(pa.array(fit))

    side = lambda c, n, m: nodes.select(F.col("node").alias(c), F.col("n").alias(n), F.col("map").alias(m))
    rows = pairs.join(side("a", "p", "x"), "a").join(side("b", "q", "y"), "b")
    return rows.select(*pairs.columns, (F.col("p") + F.col("q")).alias("both"), "x", "y").mapInArrow(check, pairs.schema)


def members_of(docs: DataFrame, ids: DataFrame, words: int, id_col: str, text_col: str) -> DataFrame:
    """``node, members``: the sets of the documents ``ids`` (node), as bytes."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([shingles(t.as_py(), words).tobytes() for t in batch.column(1)], pa.binary())], names=["node", "members"])
        trim()

    texts = docs.select(F.col(id_col).cast("bigint").alias("node"), text_col).where(F.col("node").isNotNull())
    # an id that repeats with another text has several sets, each of which links it
    return texts.join(broadcast_if(ids, ids.count(), BROADCAST_IDS), "node", "left_semi").mapInArrow(read, "node bigint, members binary").distinct()


def verified(pairs: DataFrame, members: DataFrame, similarity: Fraction) -> DataFrame:
    """The ``pairs`` (a, b) whose sets have the similarity or more."""
    num, den = similarity.numerator, similarity.denominator

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = np.frombuffer(x.as_py(), dtype=np.int64), np.frombuffer(y.as_py(), dtype=np.int64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(both * den >= (len(x) + len(y) - both) * num)
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))
        trim()

    sides = pairs.join(members.select(F.col("node").alias("a"), F.col("members").alias("x")), "a").join(members.select(F.col("node").alias("b"), F.col("members").alias("y")), "b")
    return cut(sides.select("a", "b", "x", "y").mapInArrow(check, "a bigint, b bigint").distinct())


def link(nodes: DataFrame, docs: DataFrame, words: int, similarity: Fraction, radius: int, id_col: str, text_col: str) -> DataFrame:
    """``node, root`` of the components of the candidates among ``nodes`` (node, n, map, f0, ...) that have the similarity or more."""
    names = [c for c in nodes.columns if c[0] == "f"]
    parts = [(c, bits, t) for c in names for bits, t in allocate_rows(*bit_statistics(nodes, c), radius, MOST_ROWS)]
    found = cut(candidates(nodes.select("node", *names), parts, len(names), radius))
    pairs = cut(possible(found.where("a <> b").select("a", "b", "distance"), nodes.select("node", "n", "map"), similarity))
    crowded = found.where("crowded = 1").select(F.col("a").alias("node")).distinct()
    ids = cut(pairs.select(F.explode(F.array("a", "b")).alias("node")).unionByName(crowded).distinct())
    members = cut(members_of(docs, ids, words, id_col, text_col))
    nearest = pairs.groupBy("a").agg(F.min(F.struct("distance", "b")).alias("x")).select("a", F.col("x.b").alias("b"))
    edges = verified(nearest, members, similarity)
    roots = components(edges)
    size = roots.count()

    def rooted(df: DataFrame, c: str) -> DataFrame:
        own = roots.select(F.col("node").alias(c), F.col("root").alias(f"root_{c}"))
        return df.join(broadcast_if(own, size, BROADCAST_IDS), c, "left").withColumn(f"root_{c}", F.coalesce(f"root_{c}", c))

    rest = rooted(rooted(pairs.select("a", "b"), "a"), "b").where("root_a <> root_b").select("a", "b")
    dense = rooted(nodes.join(crowded, "node", "left_semi"), "node")
    dense = cut(dense.select("node", *names, F.col("root_node").alias("root"), F.col("n").cast("bigint").alias("n"), *SHORT))
    if not dense.isEmpty():
        across = crossing(dense, parts, len(names), radius, similarity)
        rest = rest.unionByName(possible(across, nodes.select("node", "n", "map"), similarity)).distinct()
    rest = cut(rest.join(nearest, ["a", "b"], "left_anti"))
    # the first components stand for their edges: if nothing joins them, they are the result
    return components(roots.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(verified(rest, members, similarity)))


def groups(docs: DataFrame, words: int, similarity: str, families: int, radius: int | None, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """(sketches of all rows, ``d0, d1, component, copies`` of every set), both materialised."""
    exact = Fraction(similarity)
    needs_integer_ids(docs, id_col)
    found = cut(sketches(docs, words, families, id_col, text_col))
    names = ["n", "map", *(f"f{i}" for i in range(families)), *SHORT]
    sets = found.groupBy("d0", "d1").agg(F.min(id_col).cast("bigint").alias("node"), F.min(F.struct(*names)).alias("x"), F.count(F.lit(1)).alias("copies"))
    sets = cut(sets.select("d0", "d1", "node", "copies", "x.*"))
    # an id with several texts is one node; its sets are all checked, and each one's fingerprints find candidates
    nodes = sets.where("node IS NOT NULL").select("node", *names)
    roots = link(nodes, docs, words, exact, radius or bits_for(float(exact), 1), id_col, text_col)
    return found, cut(sets.join(roots, "node", "left").select("d0", "d1", F.coalesce("root", "node").alias("component"), "copies"))


def _with_component(rows: DataFrame, of: DataFrame) -> DataFrame:
    """``rows`` with the component of their sets (d0, d1)."""
    total = of.agg(F.coalesce(F.sum("copies"), F.lit(0)).alias("n")).first()["n"]
    hot = of.where(F.col("copies") > max(HOT_ROWS, HOT_SHARE * total))
    return join_hot(rows, of.drop("copies"), ["d0", "d1"], hot)


def near_duplicates(docs: DataFrame, words: int, similarity: str = "0.8", families: int = FAMILIES, radius: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, n, component`` for each row; the component is the least id linked directly or through others.

    ``radius`` defaults to the bits in which fingerprints at the similarity are expected to differ.
    """
    found, of = groups(docs, words, similarity, families, radius, id_col, text_col)
    return _with_component(found.select(id_col, "n", "d0", "d1"), of).select(id_col, "n", "component")


def keep_first(docs: DataFrame, words: int, similarity: str = "0.8", families: int = FAMILIES, radius: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each group of near copies: the text of its least id, once even if rows repeat it. Rows of null ids stay only where no
    row with an id has their set of shingles, one for each such set. All columns of ``docs`` stay."""
    found, of = groups(docs, words, similarity, families, radius, id_col, text_col)
    owned = _with_component(found.where(F.col(id_col).isNotNull()).select(id_col, "d0", "d1"), of)
    repeated = found.where(F.col(id_col).isNotNull()).groupBy(id_col).count().where("count > 1").select(id_col)
    dropped = cut(owned.where(F.col(id_col) != F.col("component")).select(id_col).unionByName(repeated).distinct())
    several = cut(repeated)
    plain = docs.where(F.col(id_col).isNotNull()).join(broadcast_if(dropped, dropped.count(), BROADCAST_IDS), id_col, "left_anti").select(docs.columns)
    if several.isEmpty() and docs.where(F.col(id_col).isNull()).isEmpty():
        return plain
    odd = docs.where(F.col(id_col).isNull()).unionByName(docs.join(broadcast_if(several, several.count(), BROADCAST_IDS), id_col, "left_semi").select(docs.columns))
    at = docs.columns.index(text_col)

    def digested(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            d = np.array([digest(shingles(t.as_py(), words)) for t in batch.column(at)], dtype=np.int64).reshape(-1, 2)
            whole = pa.StructArray.from_arrays(batch.columns, fields=list(batch.schema))
            yield pa.RecordBatch.from_arrays([whole, pa.array(d[:, 0]), pa.array(d[:, 1])], names=["row", "d0", "d1"])

    rows = odd.mapInArrow(digested, f"row {docs.schema.simpleString()}, d0 bigint, d1 bigint")
    judged = _with_component(rows, of).where(F.col("component").isNull() | (F.col(f"row.`{id_col}`") == F.col("component")))
    # an id that has several texts keeps the least row of its component; rows without any id one for each set
    key = [F.col("component"), F.when(F.col("component").isNull(), F.col("d0")).alias("k0"), F.when(F.col("component").isNull(), F.col("d1")).alias("k1")]
    first = judged.groupBy(*key).agg(F.min("row").alias("row"))
    return plain.unionByName(first.select("row.*"))
