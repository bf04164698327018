"""Readers and writers around the engine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
TRIPLES = "subject string, attr string, object string"


def read_tables(spark: SparkSession, sf_dir: str, columns: dict[str, list[str]] | None = None) -> dict[str, DataFrame]:
    """The given tables, with only the columns asked for."""
    out = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in (columns or TABLES)}
    return {t: df.select(*columns[t]) if columns and columns[t] else df for t, df in out.items()}


def read_triples(spark: SparkSession, path: str, fmt: str = "csv", **options: str) -> DataFrame:
    """``subject, attr, object`` from csv, json, orc or parquet."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(TRIPLES) if fmt in ("csv", "json") else reader).load(path).select("subject", "attr", "object")


def page_fields(html: Column) -> Column:
    """Title and links of a page as a struct."""
    return F.struct(F.regexp_extract(html, r"(?s)<title>(.*?)</title>", 1).alias("title"), F.regexp_extract_all(html, F.lit(r'href="([^"]*)"'), F.lit(1)).alias("links"))


def write_answer(answer: DataFrame, path: str, fmt: str = "parquet") -> None:
    """One table answer; names are made safe for formats that forbid marks in them."""
    safe = answer.toDF(*(c.replace(".", "_").replace(" ", "_").replace("(", "").replace(")", "") for c in answer.columns))
    safe.write.mode("overwrite").format(fmt).option("header", "true").save(path)


def register(answer: DataFrame, name: str) -> None:
    answer.createOrReplaceTempView(name)
