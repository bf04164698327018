"""Searches as SQL text over the registered views, and table functions for SQL users."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..functions.scoring import DIGITS


def search_sql(words: list[str], k: int = 100, per_type: bool = False, prefix: str = "kg") -> str:
    """A ranked search (product validity, usual factors) over the views of ``PathIndex.register_views``.

    ``per_type`` keeps k patterns of each root type before the last cut.
    """
    words = list(dict.fromkeys(words))
    if any(not w.isalnum() for w in words):
        raise ValueError("words are letters and digits")
    ids = [f"p{i}" for i in range(1, len(words) + 1)]
    parts = [f"w{i} AS (SELECT root, root_type, pattern_id AS p{i}, len AS len{i}, pr AS pr{i}, sim AS sim{i} FROM {prefix}_postings WHERE word = '{w}')" for i, w in enumerate(words, 1)]
    total = {c: " + ".join(f"{c}{i}" for i in range(1, len(words) + 1)) for c in ("len", "pr", "sim")}
    joins = " ".join(f"JOIN w{i} USING (root, root_type)" for i in range(2, len(words) + 1))
    decade = "FLOOR(LOG10(score))"
    order = f"CAST(ROUND(({decade} * 9 + score / POWER(10.0D, {decade})) * {10**DIGITS}L) AS BIGINT) DESC, {', '.join(ids)}"
    ranked = f"SELECT *, ROW_NUMBER() OVER (PARTITION BY root_type ORDER BY {order}) AS place FROM scored" if per_type else "SELECT *, 1 AS place FROM scored"
    return f"""WITH {', '.join(parts)},
scored AS (SELECT root_type, {', '.join(ids)}, COUNT(*) AS n_trees, SUM(({total['pr']}) * ({total['sim']}) / ({total['len']})) AS score FROM w1 {joins} GROUP BY root_type, {', '.join(ids)}),
kept AS ({ranked})
SELECT root_type, ARRAY({', '.join(ids)}) AS pattern_ids, n_trees, score FROM kept WHERE place <= {k} ORDER BY {order} LIMIT {k}"""


@udtf(returnType="pos: int, word: string")
class QueryWords:
    """``query_words(text)``: position and word of each distinct word."""

    def eval(self, text: str):
        import re

        for pos, word in enumerate(dict.fromkeys(w for w in re.split(r"[^a-z0-9]+", (text or "").lower()) if w)):
            yield pos, word


@udtf(returnType="place: int, label: int, is_attr: boolean")
class PatternCells:
    """``pattern_cells(labels)``: the labels of a path pattern one by one, with whether they are attributes."""

    def eval(self, labels: list[int]):
        for place, label in enumerate(labels or []):
            yield place, label, place % 2 == 1


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("query_words", QueryWords)
    spark.udtf.register("pattern_cells", PatternCells)
