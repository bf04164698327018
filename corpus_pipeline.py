"""A corpus pipeline from five operators: language, near duplicates, benchmark leaks, secrets, tokens.

Each stage gets what its predecessor kept as ``docs`` and returns the columns of ``documents`` (the last adds the
encoding). Stages call the operators of ``kwtables.llm``; nothing here is limited to part of the table. Every stage judges
row by row what its text says, so null and repeated ids need no care of the caller; an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kwtables.llm import bpe, decontaminate, langid, near_copies, secret_scan
from kwtables.llm.common import cut
from kwtables.llm.queries import held_out, tokenizer_path

SHINGLE, SIMILARITY = 5, "0.8"


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops what the language classifier rejects: null texts, texts without letters, and texts far from every learned language.

    Repeated rows are judged alike; without any labelled row nothing can be identified and nothing stays.
    """
    return langid.keep_identified(docs, langid.train(docs, ~held_out()))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one row of each group of near copies (SimHash candidates of five-word shingles, exact Jaccard similarity 0.8 or more):
    that of the least id, once if it repeats. Null and wordless texts are one group; rows of null ids stay only where no row
    with an id has their text, one for each such text."""
    return near_copies.keep_first(docs, SHINGLE, SIMILARITY)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops rows whose text holds a benchmark passage of ten words or more (a shorter item: the whole item).

    Rows are told apart by id and text, so a null id is judged as well and a clean text stays beside a leaked one of its id.
    """
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces secrets by a mask and sets ``n_chars`` to the new length (null for null texts; added if absent); every row stays."""
    return secret_scan.redact_documents(docs).withColumn("n_chars", F.length("text").cast("bigint"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Digests of the token ids of every row and of the text decoded from them; null texts have no tokens."""
    return bpe.encode_digests(docs, tokenizer_path())


STAGES = [
    ("language_id", identify_language),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("secrets", mask_secrets),
    ("bpe", encode),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each one's result is materialised in the shared folder before the next reads it."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)


#: Language, fingerprints and tokens are not expressible in SQL; the pipeline is tested stage by stage.
ORACLE_SQL = None
