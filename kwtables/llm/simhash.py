"""SimHash near-duplicates with a generalised pigeonhole: correlated bits grouped, thresholds chosen by cost.

Fingerprints whose bits differ in at most ``radius`` places are linked; links are closed into components. With the bits
split into m parts and part thresholds that add up to radius - m + 1 (-1 leaves a part out), any linked pair is within the
threshold in some part. Bits that go together are put into one part, so that parts are nearly independent, and the
thresholds are chosen by dynamic programming over the estimated candidates and probes of each part; estimates come from bit
and bit-pair counts over all distinct fingerprints. A fingerprint is stored under its own value in each part, and probes the
values within the threshold whose topmost changed bit it has itself: of two fingerprints exactly one probes the other.

Buckets (part, value) are compared in blocks of bounded size, so a hot bucket becomes several tasks, and each task reports
a spanning forest of the links it has verified, never all pairs of a group. Equal fingerprints are one node from the start.
Components come from repeated star contraction of the reported edges on the cluster. Ids must be integers (else TypeError).

Defined results: null or wordless texts have fingerprint zero and are linked like any other; texts with fewer words than
a shingle are one shingle; the component is the least id reachable; null ids cannot name a component and are left out of
it; repeated rows give repeated results; other columns are ignored.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import broadcast_if, cut, join_hot, ship

BITS = 64
SEED = 42
#: Rows of one bucket that are compared in one block; larger buckets are compared block by block.
BLOCK_ROWS = 4_096
#: Pairs compared at once.
CHUNK_PAIRS = 1 << 20
#: What one probe costs in comparisons: a few microseconds of work, but above all the bytes that it writes and moves.
PROBE_COST = 1_000
#: Large buckets within this number are broadcast; beyond it they are joined by shuffle.
BROADCAST_BUCKETS = 200_000
#: A key is hot at so many rows, or at this share of all rows if that is more: so there are at most 100,000 hot keys.
HOT_ROWS, HOT_SHARE = 2_000, 1e-5


def _mix(h: np.ndarray, salt: int) -> np.ndarray:
    """Another hash family from 64-bit hashes."""
    z = h + np.uint64(salt * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


def _majority(h: np.ndarray) -> int:
    """Bits set in over half of the hashes, summed in blocks that keep long texts small."""
    count = np.zeros(BITS, dtype=np.int64)
    for i in range(0, len(h), 8192):
        count += np.unpackbits(h[i : i + 8192].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return int(np.packbits(2 * count > len(h), bitorder="little").view("<u8")[0])


def fingerprint(text: str | None, shingle: int, families: int = 1) -> list[int]:
    """Fingerprints of lower-cased word shingles; repeats count, and the first family is XXH64 itself."""
    from xxhash import xxh64_intdigest

    tokens = (text or "").encode().lower().split()
    if not tokens:
        return [0] * families
    joined = b" ".join(tokens)
    ends = np.cumsum(np.fromiter(map(len, tokens), dtype=np.int64, count=len(tokens)) + 1) - 1
    if len(tokens) < shingle:
        starts, stops = [0], [len(joined)]
    else:
        starts = [0, *(ends[: len(tokens) - shingle] + 1).tolist()]
        stops = ends[shingle - 1 :].tolist()
    h = np.fromiter([xxh64_intdigest(joined[a:b], SEED) for a, b in zip(starts, stops, strict=True)], dtype=np.uint64, count=len(starts))
    return [_majority(h if f == 0 else _mix(h, f)) for f in range(families)]


def fingerprints(docs: DataFrame, shingle: int, families: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, f0, f1, ...`` (64 bits each, as long) for each row."""
    ship(docs.sparkSession)
    names = [f"f{i}" for i in range(families)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [fingerprint(t.as_py(), shingle, families) for t in batch.column(1)]
            f = np.array(found, dtype=np.uint64).reshape(-1, families).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(f[:, i]) for i in range(families))], names=[id_col, *names])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, " + ", ".join(f"{n} bigint" for n in names))


def bit_statistics(nodes: DataFrame, column: str = "f0") -> tuple[int, np.ndarray]:
    """(number of nodes, how many have both bits i and j), over all nodes; one small table for each task is added up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros((BITS, BITS)), 0
        for batch in batches:
            f = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            b = np.unpackbits(np.ascontiguousarray(f).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.float64)
            total += b.T @ b
            n += len(f)
        if n:
            cells = np.append(total.ravel(), n).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(cells))), pa.array(cells)], names=["cell", "n"])

    rows = nodes.select(column).mapInArrow(run, "cell bigint, n bigint").groupBy("cell").agg(F.sum("n").alias("n")).collect()  # 4,097 rows at most
    out = np.zeros(BITS * BITS + 1)
    for r in rows:
        out[r["cell"]] = r["n"]
    return int(out[-1]), out[:-1].reshape(BITS, BITS)


def group_bits(n: int, joint: np.ndarray, parts: int) -> list[list[int]]:
    """``parts`` groups of near-equal size; each grows from a free bit by the bit most correlated with its members."""
    p = joint.diagonal() / max(n, 1)
    spread = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    corr = np.abs((joint / max(n, 1) - np.outer(p, p)) / np.outer(spread, spread))
    free, out = list(range(BITS)), []
    for k in range(parts):
        size = len(free) // (parts - k)
        group = [free.pop(0)]
        while len(group) < size:
            best = max(free, key=lambda b: (corr[b, group].sum(), -b))
            free.remove(best)
            group.append(best)
        out.append(sorted(group))
    return out


def within(joint_p: np.ndarray, group: list[int], most: int) -> list[float]:
    """Chance that two nodes differ in at most t bits of ``group``, for t = 0..most, taking its bits as independent."""
    dist = np.zeros(most + 2)
    dist[0] = 1
    for b in group:
        d = 2 * joint_p[b] * (1 - joint_p[b])
        dist[1:] = dist[1:] * (1 - d) + dist[:-1] * d
        dist[0] *= 1 - d
    return np.cumsum(dist[: most + 1]).tolist()


def allocate(n: int, joint: np.ndarray, radius: int, probe_cost: float = PROBE_COST) -> list[tuple[list[int], int]]:
    """(bits, threshold) of each used part: the split and thresholds of least estimated cost."""
    p = joint.diagonal() / max(n, 1)
    best: tuple[float, list[tuple[list[int], int]]] = (math.inf, [])
    for m in range(1, radius + 2):
        groups, budget = group_bits(n, joint, m), radius - m + 1
        tops = range(-1, budget + m)
        # least cost and choice for each sum of thresholds so far
        table: dict[int, tuple[float, tuple[int, ...]]] = {0: (0.0, ())}
        for i, g in enumerate(groups):
            chance = within(p, g, min(budget + m, len(g)))
            grown: dict[int, tuple[float, tuple[int, ...]]] = {}
            for (total, (cost, chosen)), t in itertools.product(table.items(), tops):
                if t >= len(chance) or t > 4 or total + t > budget + (len(groups) - i - 1):
                    continue
                new = cost + (n * probe_cost * stored_rows(len(g), t) + n * n / 2 * chance[t] if t >= 0 else 0)
                if new < grown.get(total + t, (math.inf,))[0]:
                    grown[total + t] = (new, (*chosen, t))
            table = grown
        if budget in table and table[budget][0] < best[0]:
            best = (table[budget][0], [(g, t) for g, t in zip(groups, table[budget][1], strict=True) if t >= 0])
    return best[1]


def stored_rows(bits: int, threshold: int) -> float:
    """Rows that a fingerprint has in a part, on average: its own value and half of the values within the threshold."""
    return sum(math.comb(bits, j) for j in range(1, threshold + 1)) / 2 + 1


def allocate_rows(n: int, joint: np.ndarray, radius: int, most_rows: float) -> list[tuple[list[int], int]]:
    """The allocation of fewest comparisons whose rows for each fingerprint stay within ``most_rows``, for the least cost of a probe that does so."""
    for cost in (30 * 2**i for i in range(40)):
        parts = allocate(n, joint, radius, cost)
        if sum(stored_rows(len(g), t) for g, t in parts) <= most_rows:
            break
    return parts


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def probes(value: Column, part: int, bits: list[int], threshold: int) -> Column:
    """Array of (part, value, role): role 0 for the own value, 1 for each value this fingerprint probes."""
    mask = _signed(sum(1 << b for b in bits))
    own = F.array(F.struct(F.lit(part).alias("part"), value.bitwiseAND(mask).alias("value"), F.lit(0).alias("role")))
    changes = [(_signed(sum(1 << b for b in c)), _signed(1 << max(c))) for k in range(1, threshold + 1) for c in itertools.combinations(bits, k)]
    if not changes:
        return own
    table = F.array(*(F.struct(F.lit(c).alias("change"), F.lit(top).alias("top")) for c, top in changes)) if len(changes) <= 64 else F.from_json(F.lit("[" + ",".join(f'{{"change":{c},"top":{top}}}' for c, top in changes) + "]"), "array<struct<change:bigint,top:bigint>>")
    mine = F.filter(table, lambda x: value.bitwiseAND(x["top"]) != 0)
    return F.concat(own, F.transform(mine, lambda x: F.struct(F.lit(part).alias("part"), value.bitwiseAND(mask).bitwiseXOR(x["change"]).alias("value"), F.lit(1).alias("role"))))


def _forest(buckets: np.ndarray, role: np.ndarray, node: np.ndarray, f: np.ndarray, probed: int, radius: int, radius_all: int | None) -> tuple[np.ndarray, np.ndarray]:
    """Spanning edges (node, least node) of the verified links among rows of equal bucket; rows come sorted by bucket, role."""
    n = len(node)
    change = np.flatnonzero(np.append(buckets[1:] != buckets[:-1], True))
    ends = np.repeat(change + 1, np.diff(np.append(-1, change)))
    first = np.flatnonzero(role == 0)
    lens = ends[first] - first - 1
    first, lens = first[lens > 0], lens[lens > 0]
    label = np.arange(n)
    at = 0
    while at < len(first):
        reach = np.cumsum(lens[at:])
        stop = at + max(1, int(np.searchsorted(reach, CHUNK_PAIRS, side="right")))
        i = np.repeat(first[at:stop], lens[at:stop])
        j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(lens[at:stop]) - lens[at:stop], lens[at:stop])
        near = np.bitwise_count(f[i, 0] ^ f[j, 0]) <= radius
        for c in range(1, probed):
            near |= np.bitwise_count(f[i, c] ^ f[j, c]) <= radius
        i, j = i[near], j[near]
        if radius_all is not None and len(i):
            near = np.bitwise_count(f[i] ^ f[j]).sum(axis=1, dtype=np.int32) <= radius_all
            i, j = i[near], j[near]
        while len(i):
            low = np.minimum(label[i], label[j])
            np.minimum.at(label, label[i], low)
            np.minimum.at(label, label[j], low)
            np.minimum.at(label, i, low)
            np.minimum.at(label, j, low)
            while (label != label[label]).any():
                label = label[label]
            open_ = label[i] != label[j]
            i, j = i[open_], j[open_]
        at = stop
    joined = np.flatnonzero(label != np.arange(n))
    a, b = node[joined], node[label[joined]]
    return a[a != b], b[a != b]


def deal(nodes: DataFrame, parts: list[tuple[str, list[int], int]]) -> DataFrame:
    """``bucket, ...``: the columns of ``nodes`` (node, ...) once for each stored or probed value of the ``parts`` (column, bits,
    threshold), dealt and sorted by bucket; its lowest bit sorts stored values before probes. Large buckets come block by block."""
    columns = nodes.columns
    every = F.concat(*(probes(F.col(c), i, bits, t) for i, (c, bits, t) in enumerate(parts)))
    rows = nodes.select(*columns, F.explode(every).alias("x")).select("x.part", "x.value", "x.role", *columns)
    large = cut(rows.groupBy("part", "value").count().where(F.col("count") > BLOCK_ROWS))
    rows = rows.join(broadcast_if(large, large.count(), BROADCAST_BUCKETS), ["part", "value"], "left")
    blocks = F.ceil(F.coalesce("count", F.lit(1)) / BLOCK_ROWS).cast("int")
    own = F.pmod(F.xxhash64("node"), blocks).cast("int")
    rows = rows.withColumn("blocks", blocks).withColumn("own", own)
    pairs = F.when(F.col("blocks") == 1, F.array(F.lit(0))).otherwise(F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda k: F.least(k, F.col("own")) * F.col("blocks") + F.greatest(k, F.col("own"))))
    rows = rows.select("part", "value", F.explode(pairs).alias("pair"), "role", *columns)
    key = F.xxhash64("part", "value", "pair").bitwiseAND(F.lit(-2)).bitwiseOR(F.col("role").cast("bigint"))
    return rows.select(key.alias("bucket"), *columns).repartition(F.shiftright("bucket", 1)).sortWithinPartitions("bucket")


def whole_buckets(batches: Iterator[pa.RecordBatch], most: int = 100_000) -> Iterator[np.ndarray]:
    """The rows of sorted ``batches`` as matrices of whole buckets, of ``most`` rows or more unless the rows end."""
    held: list[np.ndarray] = []
    size = 0
    for batch in batches:
        held.append(np.stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in batch.columns], axis=1))
        size += len(held[-1])
        if size < most:
            continue
        data = np.concatenate(held)
        last = int(np.searchsorted(data[:, 0] >> 1, data[-1, 0] >> 1))  # the last bucket may go on
        if last:
            yield data[:last]
        held, size = [data[last:]], 0
    if held:
        yield np.concatenate(held)


def link(nodes: DataFrame, radius: int, radius_all: int | None = None, probed: int = 1) -> DataFrame:
    """Edges ``a, b`` that connect whatever ``nodes`` (node, f0, ...) link: at ``radius`` bits of one of the first ``probed``
    families, and at ``radius_all`` bits of all families together if given."""
    ship(nodes.sparkSession)
    families = [c for c in nodes.columns if c != "node"]
    parts = [(c, bits, t) for c in families[:probed] for bits, t in allocate(*bit_statistics(nodes, c), radius)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for data in whole_buckets(batches):
            a, b = _forest(data[:, 0] >> 1, data[:, 0] & 1, data[:, 1], np.ascontiguousarray(data[:, 2:]).view(np.uint64), probed, radius, radius_all)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    return deal(nodes.select("node", *families), parts).mapInArrow(run, "a bigint, b bigint")


def components(edges: DataFrame, most_rounds: int = 50) -> DataFrame:
    """``node, root`` for every node of ``edges`` (a, b): root is the least node of its component. Star contraction, cut every round;
    the centres of large stars are joined by broadcast, so that no task has a whole star."""
    pairs = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    for _ in range(most_rounds):
        turned = pairs.select(F.col("v").alias("u"), F.col("u").alias("v"))
        around = pairs.unionByName(turned).groupBy("u").agg(F.min("v").alias("m"), F.count("v").alias("n"), F.count_if(F.col("v") < F.col("u")).alias("lower"))
        around = cut(around.select("u", F.least("u", "m").alias("m"), "n", "lower"))
        none = F.lit(0)
        state = around.agg(F.coalesce(F.sum("n"), none).alias("n"), F.coalesce(F.max("n"), none).alias("most"), F.count_if((F.col("lower") > 0) & (F.col("n") > 1)).alias("open")).first()
        # stars only, each leaf under one root: nothing changes any more
        if not state["open"]:
            return pairs.select(F.col("u").alias("node"), F.col("v").alias("root"))
        bound = max(HOT_ROWS, HOT_SHARE * state["n"])
        least = around.select("u", "m")
        named = join_hot(turned, least, ["u"], around.where(F.col("n") > bound).select("u")) if state["most"] > bound else turned.join(least, "u")
        large = cut(named.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct())
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct("v", "m"), F.struct(F.col("u").alias("v"), "m"))).alias("x")).select(F.col("x.v").alias("u"), F.col("x.m").alias("v"))
        pairs = cut(small.where("u <> v").distinct())
    raise RuntimeError(f"components still open after {most_rounds} rounds")


def near_duplicates(docs: DataFrame, shingle: int, radius: int, families: int = 1, radius_all: int | None = None, probed: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, f0, ..., component`` for each row; the component is the least id linked directly or through others."""
    needs_integer_ids(docs, id_col)
    prints = cut(fingerprints(docs, shingle, families, id_col, text_col))
    names = [f"f{i}" for i in range(families)]
    nodes = cut(prints.groupBy(*names).agg(F.min(id_col).cast("bigint").alias("node"), F.count(F.lit(1)).alias("copies")))
    roots = components(link(nodes.where("node IS NOT NULL").select("node", *names), radius, radius_all, probed))
    named = cut(nodes.join(roots, "node", "left").select(*names, F.coalesce("root", "node").alias("component"), "copies"))
    total = named.agg(F.coalesce(F.sum("copies"), F.lit(0)).alias("n")).first()["n"]
    hot = named.where(F.col("copies") > max(HOT_ROWS, HOT_SHARE * total))
    return join_hot(prints, named.drop("copies"), names, hot).select(id_col, *names, "component")


def needs_integer_ids(docs: DataFrame, id_col: str) -> None:
    """Components are named by the least id, an integer."""
    if docs.schema[id_col].dataType.simpleString() not in ("tinyint", "smallint", "int", "bigint"):
        raise TypeError(f"integer ids are needed, {id_col!r} is {docs.schema[id_col].dataType.simpleString()}")


def bits_for(similarity: float, families: int) -> int:
    """Differing bits that shingle sets of this Jaccard similarity are expected to show over ``families`` fingerprints."""
    return math.floor(families * BITS * math.acos(2 * similarity / (1 + similarity)) / math.pi)
