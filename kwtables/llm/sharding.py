"""Proportional stratified interleaving: every shard gets the corpus mixture of sources.

Rows of a source are put in a seeded random order; the row at place i of n has the fractional rank (i + 1/2) / n.
Sorted by that rank, any stretch of the corpus holds each source in proportion, so equal cuts of the order are
shards that all match the mixture; their sizes in rows differ by one at most.

No window holds a whole source or the whole corpus: both orders are cut into cells (of the seeded hash, then of the
fractional rank) whose rows are ranked alone and then shifted by the running total of the cells before, a table of
as many rows as there are cells. The hash makes the cells even, whatever the source's share. It is the first 60 bits of
an MD5 digest of seed and id, so that any SQL engine finds the same order.

Defined results: null sources form one stratum; null text has size 1 and the checksum of no bytes; equal texts are
no constraint under the ``rows`` law; rows of null ids are spread by a hash of the whole row; rows of a repeated id follow each other by a hash of the whole row, so that a task
that runs again places them alike (equal rows are interchangeable); an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import broadcast_if

SEED = "interleave"
#: Rows that a cell holds on average, as long as that makes no more than MOST_CELLS cells.
CELL_ROWS = 4_096
MOST_CELLS = 65_536
#: Offset tables of up to this many rows are broadcast; beyond it they are joined by shuffle.
BROADCAST_ROWS = 200_000
ORDER_BITS = 60


def interleave(docs: DataFrame, shards: int = 16, id_col: str = "doc_id", source_col: str = "source", seed: str = SEED, cell_rows: int = CELL_ROWS) -> DataFrame:
    """Every row of ``docs`` with ``shard`` (0 to shards-1) and ``slot`` (gapless from 0 within the shard).

    Columns of ``docs`` with those two names are replaced; any other column stays, whatever its name.
    """
    kept = [F.col(f"`{c}`") for c in docs.columns if c.lower() not in ("shard", "slot")]
    stratum = F.coalesce(F.col(source_col).cast("string"), F.lit("\0null"))
    hashed = [F.col(f"`{f.name}`") for f in docs.schema if not any(t in f.dataType.simpleString() for t in ("map<", "variant"))]
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(id_col).cast("string"), F.concat(F.lit("null:"), F.xxhash64(*hashed).cast("string")))).cast("binary"))
    order = F.conv(F.substring(digest, 1, ORDER_BITS // 4), 16, 10).cast("bigint")
    rows = docs.select(F.struct(*kept).alias("row"), F.col(id_col).alias("id"), stratum.alias("stratum"), order.alias("order"), F.xxhash64(*hashed).alias("tie"))
    sizes = rows.groupBy("stratum").count()
    totals = sizes.agg(F.count(F.lit(1)).alias("strata"), F.coalesce(F.sum("count"), F.lit(0)).alias("rows"), F.coalesce(F.max("count"), F.lit(0)).alias("largest")).first()
    n, strata = totals["rows"], totals["strata"]

    cells = min(MOST_CELLS, 1 << (totals["largest"] // cell_rows).bit_length())
    rows = rows.withColumn("cell", F.shiftright("order", ORDER_BITS - cells.bit_length() + 1).cast("int") if cells > 1 else F.lit(0))
    before = Window.partitionBy("stratum").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    offsets = rows.groupBy("stratum", "cell").count().select("stratum", "cell", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("before"), F.sum("count").over(Window.partitionBy("stratum")).alias("total"))
    ranked = rows.withColumn("place", F.row_number().over(Window.partitionBy("stratum", "cell").orderBy("order", "id", "tie")))
    ranked = ranked.join(broadcast_if(offsets, strata * cells, BROADCAST_ROWS), ["stratum", "cell"])
    fraction = (F.col("before") + F.col("place") - F.lit(0.5)) / F.col("total")

    bands = min(MOST_CELLS, max(1, -(-n // cell_rows)))
    ranked = ranked.withColumn("fraction", fraction).withColumn("band", F.least(F.floor(F.col("fraction") * bands), F.lit(bands - 1)).cast("int"))
    running = Window.orderBy("band").rowsBetween(Window.unboundedPreceding, -1)
    starts = ranked.groupBy("band").count().select("band", F.coalesce(F.sum("count").over(running), F.lit(0)).alias("start"))  # at most MOST_CELLS rows
    placed = ranked.withColumn("place", F.row_number().over(Window.partitionBy("band").orderBy("fraction", "stratum", "order", "id", "tie")))
    placed = placed.join(F.broadcast(starts), "band").withColumn("position", F.col("start") + F.col("place") - 1)
    placed = placed.withColumn("shard", F.expr(f"CAST(position * {shards} DIV {max(n, 1)} AS INT)"))
    first = F.expr(f"(CAST(shard AS BIGINT) * {max(n, 1)} + {shards - 1}) DIV {shards}")
    return placed.select("row.*", "shard", (F.col("position") - first).alias("slot"))


def slim(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with the text replaced by its size in bytes plus one and its checksum, for ordering without carrying texts."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.withColumns({"size": (F.octet_length(text) + 1).cast("bigint"), "text_crc32": F.crc32(text.cast("binary"))}).drop(text_col)


def write_shards(placed: DataFrame, path: str) -> None:
    """One folder for each shard, rows in slot order within each file."""
    placed.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.mode("overwrite").partitionBy("shard").parquet(path)
