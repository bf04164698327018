"""One query for each training-data operator, over its whole table with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, decontaminate, html_wrapper, langid, mpegts, pii, secret_scan, sharding, simhash, token_count

TOKENIZER = "byte_bpe_50k.json"
TOKEN_LIMIT = 1024


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(TOKENIZER)


def _documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", *columns)


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def _count(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("bigint")


def op1_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    return html_wrapper.extract_pages(pages).withColumn("n_chars", F.length("text").cast("bigint"))


def op2_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(_documents(spark, sf_dir, "text"), tokenizer_path())


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    out = decontaminate.find_overlaps(_documents(spark, sf_dir, "text"), items)
    return out.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("bigint").alias("n_items"), F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op4_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = simhash.near_duplicates(_documents(spark, sf_dir, "text"), shingle=4, radius=4)
    return out.select("doc_id", F.lpad(F.lower(F.hex("f0")), 16, "0").alias("fingerprint"), F.col("component").alias("component_id"))


def held_out() -> Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir, "text", "lang")
    model = langid.train(docs, ~held_out())
    return langid.predict(docs, model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "rejected")


def op6_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find_personal_data(_documents(spark, sf_dir, "text"))
    counts = [_count(F.col("base"), k).alias(f"n_{k}") for k in pii.BASE_KINDS]
    return found.select("doc_id", *counts, F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"))


def op7_transport_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mpegts.round_trip_digests(_documents(spark, sf_dir, "text"))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    counted = token_count.count_tokens(_documents(spark, sf_dir, "text"), tokenizer_path())
    return counted.withColumn("over_limit", F.col("n_tokens") > TOKEN_LIMIT)


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secret_scan.scan_documents(_documents(spark, sf_dir, "text"))
    counts = [_count(F.col("base"), k).alias(f"n_{k}") for k in secret_scan.PATTERN_KINDS]
    return found.select("doc_id", *counts, F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"))


def op10_interleaved_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.interleave(sharding.slim(_documents(spark, sf_dir, "source", "text")), shards=16)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_html_main_text, op2_bpe_round_trip, op3_decontamination, op4_simhash_components, op5_language_id, op6_personal_data, op7_transport_stream, op8_token_counts, op9_secret_scan, op10_interleaved_shards)}


#: Runs of ten words (shorter items: the whole item) of documents and items are joined as strings.
OP3_SQL = r"""
WITH doc AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents
), item AS (
  SELECT CAST(item_id AS VARCHAR) AS item, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark
), item_run AS (
  SELECT item, least(len(w), 10) AS n, array_to_string(w[i : i + least(len(w), 10) - 1], ' ') AS run
  FROM item, LATERAL (SELECT unnest(range(1, len(w) - least(len(w), 10) + 2)) AS i)
  WHERE len(w) > 0
), lengths AS (
  SELECT DISTINCT n FROM item_run
), doc_run AS (
  SELECT doc_id, n, i, array_to_string(w[i : i + n - 1], ' ') AS run
  FROM doc, lengths, LATERAL (SELECT unnest(range(1, len(w) - n + 2)) AS i)
), hit AS (
  SELECT doc_id, i, d.n, item FROM doc_run d JOIN item_run b ON d.n = b.n AND d.run = b.run
), covered AS (
  SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT DISTINCT doc_id, i, n FROM hit), LATERAL (SELECT unnest(range(i, i + n)) AS p) GROUP BY doc_id
), matched AS (
  SELECT doc_id, count(DISTINCT item) AS n_items, sha256(string_agg(DISTINCT item, ',' ORDER BY item)) AS items_sha256 FROM hit GROUP BY doc_id
)
SELECT doc.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  coalesce(items_sha256, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM doc LEFT JOIN covered ON doc.doc_id = covered.doc_id LEFT JOIN matched ON doc.doc_id = matched.doc_id
"""


#: Fractional ranks by windows over whole sources; the checksum runs over the bytes with a table made by its rule.
OP10_SQL = r"""
WITH step AS (
  SELECT list_transform(range(256), lambda n: list_reduce([n, 0, 0, 0, 0, 0, 0, 0, 0], lambda c, x: xor(c >> 1, 3988292384 * (c & 1)))) AS t
), doc AS (
  SELECT doc_id, coalesce(source, chr(0) || 'null') AS stratum, encode(coalesce(text, '')) AS body,
    CAST('0x' || substr(md5('interleave:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) AS o
  FROM documents
), summed AS (
  SELECT doc_id, stratum, o, octet_length(body) + 1 AS size,
    xor(4294967295, list_reduce(list_prepend(CAST(4294967295 AS BIGINT), list_transform(regexp_extract_all(hex(body), '..'), lambda h: CAST('0x' || h AS BIGINT))),
      lambda c, b: xor(c >> 8, t[xor(c, b) % 256 + 1]))) AS text_crc32
  FROM doc, step
), ranked AS (
  SELECT *, (row_number() OVER (PARTITION BY stratum ORDER BY o, doc_id) - CAST(0.5 AS DOUBLE)) / count(*) OVER (PARTITION BY stratum) AS fraction FROM summed
), placed AS (
  SELECT *, row_number() OVER (ORDER BY fraction, stratum, o, doc_id) - 1 AS position, count(*) OVER () AS n FROM ranked
), dealt AS (
  SELECT *, position * 16 // n AS s FROM placed
)
SELECT doc_id, CAST(size AS BIGINT) AS size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'rows' AS law, CAST(s AS INTEGER) AS shard,
  CAST(row_number() OVER (PARTITION BY s ORDER BY position) - 1 AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard
FROM dealt
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_decontamination": OP3_SQL, "op10_interleaved_shards": OP10_SQL}
