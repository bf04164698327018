"""Benchmark decontamination by winnowing, with DataFrame and SQL functions only.

Every run of ``span`` consecutive words that a document shares with a benchmark item must be found. Hashes of k-grams
of words are winnowed: of each ``span - k + 1`` consecutive k-gram hashes the least is kept, so two texts that share
such a run keep one hash in common. Documents' kept hashes are looked up among the items' (a broadcast while the items
measure up to a bound, a shuffle beyond it); documents with a hit are extended: their runs of ``span`` words are compared
as strings with the items' runs, and each word inside an occurrence counts. Items shorter than ``span`` are one run of
their own length, winnowed with a k and window that guarantee that length.

Hashes are combined by doubling (k-grams from halves, window minima from overlapping halves), so a text costs a few
array passes whatever k and the window are. Nothing grows with the size of a group: a passage that many documents share
adds rows in proportion to those documents, and a run that many items share is one row with the list of items.

Defined results: null or wordless texts have no words and no hits; wordless items have no runs; items with equal text
all count; null item ids are not counted; rows equal in id and text are looked up once and give one result each; other
columns are ignored; an empty table of documents stays empty, and without items nothing is hit.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import broadcast_if, cut

# What stands between words, and the letters that are lowered.
BREAKS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

SPAN = 10
GRAM = 4
#: Broadcast sides hold up to this many rows; beyond it the joins shuffle.
BROADCAST_ROWS = 300_000


def words(text: Column) -> Column:
    """Maximal runs of digits, letters and whatever is not ASCII, lower-cased; splitting is far cheaper than extracting matches."""
    return F.array_remove(F.split(F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER), BREAKS), "")


def _shifted(df: DataFrame, name: str, a: str, b: str, by: int, join) -> DataFrame:
    """Column ``name``: ``join(a[i], b[i + by])`` for every i where both exist; ``a`` is at least as long as ``b`` shifted."""
    n = F.greatest(F.size(b) - by, F.lit(0))
    return df.withColumn(name, F.zip_with(F.slice(a, F.lit(1), n), F.slice(b, F.lit(1 + by), n), join))


def winnow(df: DataFrame, out: str, tokens: str, span: int, gram: int = GRAM) -> DataFrame:
    """``df`` with ``out``: the distinct least k-gram hashes of array<string> ``tokens`` that any shared run of ``span`` tokens meets."""
    k = min(gram, span)
    window = span - k + 1
    held = set(df.columns)
    df = df.withColumn("_h1", F.transform(tokens, lambda w: F.xxhash64(w)))
    size = 1
    while size < k:  # gram hashes of length size + step
        step = min(size, k - size)
        df = _shifted(df, f"_h{size + step}", f"_h{size}", f"_h{step}", size, lambda a, b: F.xxhash64(a, b))
        size += step
    df, size, at = df.withColumn("_m1", F.col(f"_h{k}")), 1, "_m1"
    while size < window:  # minima over size + step hashes, halves may overlap
        step = min(size, window - size)
        df = _shifted(df, f"_m{size + step}", at, at, step, lambda a, b: F.least(a, b))
        size += step
        at = f"_m{size}"
    return df.withColumn(out, F.array_distinct(at)).select(*(c for c in df.columns if c in held), out)


def _marked(hashes: str, span: int) -> Column:
    return F.transform(hashes, lambda h: F.struct(h.alias("print"), F.lit(span).alias("print_span")))


def _runs(tokens: str, span: int) -> Column:
    """Every run of ``span`` tokens as one string, in order."""
    last = F.size(tokens) - (span - 1)
    return F.when(last >= 1, F.transform(F.sequence(F.lit(1), last), lambda i: F.array_join(F.slice(F.col(tokens), i, span), " "))).otherwise(F.array().cast("array<string>"))


#: Copies of one row are written out in groups of so many.
COPIES = 4_096


def find_overlaps(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text", span: int = SPAN, gram: int = GRAM) -> DataFrame:
    """``id_col, n_words, n_hit, item_ids`` for each row; ``item_ids`` is the sorted list (as strings) of items with a shared run."""
    out = overlaps(docs, items, id_col, text_col, item_id_col, item_text_col, span, gram)
    out = out.withColumn("lot", F.explode(F.sequence(F.lit(0), F.floor((F.col("copies") - 1) / COPIES))))
    every = F.sequence(F.lit(1), F.least(F.lit(COPIES), F.col("copies") - F.col("lot") * COPIES))
    return out.withColumn("copy", F.explode(every)).select(F.col("id").alias(id_col), "n_words", "n_hit", "item_ids")


def drop_contaminated(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text", span: int = SPAN, gram: int = GRAM) -> DataFrame:
    """The rows of ``docs`` without a hit, with all their columns; ids may be null or repeat with other texts."""
    bad = cut(overlaps(docs, items, id_col, text_col, item_id_col, item_text_col, span, gram).where("n_hit > 0").select("id", "text_hash"))
    same = F.col(f"d.`{id_col}`").eqNullSafe(F.col("b.id")) & (F.xxhash64(F.col(f"d.`{text_col}`")) == F.col("b.text_hash"))
    return docs.alias("d").join(broadcast_if(bad, bad.count(), BROADCAST_ROWS).alias("b"), same, "left_anti")


def overlaps(docs: DataFrame, items: DataFrame, id_col: str, text_col: str, item_id_col: str, item_text_col: str, span: int, gram: int) -> DataFrame:
    """``id, text_hash, copies, n_words, n_hit, item_ids``: one row for all rows of equal id and text."""
    bench = items.select(F.col(item_id_col).cast("string").alias("item"), words(F.col(item_text_col)).alias("tokens"))
    bench = bench.where(F.size("tokens") > 0).withColumn("span", F.least(F.size("tokens"), F.lit(span)))
    measured = bench.groupBy("span").agg(F.sum(F.size("tokens") - F.col("span") + 1).alias("runs")).collect()  # a row for each length up to span
    spans = sorted(r["span"] for r in measured)
    n_runs = sum(r["runs"] for r in measured)

    texts = docs.select(F.col(id_col).alias("id"), F.xxhash64(text_col).alias("text_hash"), F.col(text_col).alias("body"))
    if not spans:
        out = texts.select("id", "text_hash", F.size(words(F.col("body"))).cast("bigint").alias("n_words")).groupBy("id", "text_hash").agg(F.max("n_words").alias("n_words"), F.count(F.lit(1)).alias("copies"))
        return out.select("id", "text_hash", "copies", "n_words", F.lit(0).cast("bigint").alias("n_hit"), F.array().cast("array<string>").alias("item_ids"))

    prints, kept = None, texts.select("id", "text_hash", words(F.col("body")).alias("tokens"))
    kept = kept.withColumn("n_words", F.size("tokens").cast("bigint"))
    for s in spans:
        mine = winnow(bench.where(F.col("span") == s).select("tokens"), "kept", "tokens", s, gram).select(F.explode("kept").alias("print"), F.lit(s).alias("print_span"))
        prints = mine if prints is None else prints.unionByName(mine)
        kept = winnow(kept, f"kept_{s}", "tokens", s, gram)
    prints = prints.distinct()
    # one entry without a print for each row, by which the copies are counted
    found = F.concat(F.array(F.struct(F.lit(None).cast("bigint").alias("print"), F.lit(0).alias("print_span"))), *(_marked(f"kept_{s}", s) for s in spans))
    rows = kept.select("id", "text_hash", "n_words", F.explode(found).alias("print")).select("id", "text_hash", "n_words", "print.print", "print.print_span")
    looked_up = rows.join(broadcast_if(prints.withColumn("met", F.lit(True)), n_runs, BROADCAST_ROWS), ["print", "print_span"], "left")
    marked = cut(looked_up.groupBy("id", "text_hash").agg(F.max("n_words").alias("n_words"), F.count_if(F.col("print_span") == 0).alias("copies"), F.coalesce(F.bool_or("met"), F.lit(False)).alias("met")))

    suspects = marked.where("met").select("id", "text_hash")
    same = (F.col("t.id").eqNullSafe(F.col("s.id"))) & (F.col("t.text_hash") == F.col("s.text_hash"))
    bodies = texts.alias("t").join(broadcast_if(suspects, suspects.count(), BROADCAST_ROWS).alias("s"), same, "left_semi")
    bodies = bodies.select("id", "text_hash", words(F.col("body")).alias("tokens"))
    places = None
    for s in spans:
        mine = bodies.select("id", "text_hash", F.posexplode(_runs("tokens", s)).alias("at", "run"), F.lit(s).alias("span"))
        places = mine if places is None else places.unionByName(mine)
    wanted = None
    for s in spans:
        mine = bench.where(F.col("span") == s).select("item", "span", F.explode(_runs("tokens", s)).alias("run"))
        wanted = mine if wanted is None else wanted.unionByName(mine)
    # runs with the same items share one list of them, so that a document gathers lists, not items for each of its runs
    wanted = wanted.groupBy("run", "span").agg(F.array_sort(F.collect_set("item")).alias("items")).withColumn("list", F.sha2(F.to_json("items"), 256))
    wanted = cut(wanted)
    lists = wanted.groupBy("list").agg(F.first("items").alias("items"))
    hits = places.join(broadcast_if(wanted.select("run", "span", "list"), n_runs, BROADCAST_ROWS), ["run", "span"])
    # at most a document's own positions are gathered in its row
    inside = F.array_distinct(F.flatten(F.transform(F.collect_set(F.struct("at", "span")), lambda p: F.sequence(p["at"], p["at"] + p["span"] - 1))))
    extended = cut(hits.groupBy("id", "text_hash").agg(F.size(inside).cast("bigint").alias("n_hit"), F.collect_set("list").alias("lists")))
    named = extended.select("id", "text_hash", "n_hit", F.explode("lists").alias("list")).join(broadcast_if(lists, n_runs, BROADCAST_ROWS), "list")
    extended = named.groupBy("id", "text_hash").agg(F.max("n_hit").alias("n_hit"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("item_ids"))
    both = (F.col("m.id").eqNullSafe(F.col("e.id"))) & (F.col("m.text_hash") == F.col("e.text_hash"))
    out = marked.alias("m").join(extended.alias("e"), both, "left")
    return out.select(F.col("m.id").alias("id"), F.col("m.text_hash").alias("text_hash"), "copies", "n_words", F.coalesce("n_hit", F.lit(0)).cast("bigint").alias("n_hit"), F.coalesce("item_ids", F.array().cast("array<string>")).alias("item_ids"))
