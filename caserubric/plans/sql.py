"""The engine's SQL surface: views, functions and a table function."""

from __future__ import annotations

import re
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..tables import load, models, posts, star_cases, star_criteria, star_judged

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
WORDS = r"array_distinct(filter(regexp_extract_all(lower({0}), r'([\p{{L}}\p{{N}}]+)', 1), w -> length(w) >= 4))"
FUNCTIONS = {
    "clip01(x DOUBLE) RETURNS DOUBLE": "CASE WHEN x IS NOT NULL THEN least(greatest(x, 0.0D), 1.0D) END",
    "content_words(t STRING) RETURNS ARRAY<STRING>": WORDS.format("t"),
    "coverage(a STRING, b STRING) RETURNS DOUBLE": f"coalesce(try_divide(size(array_intersect({WORDS.format('a')}, {WORDS.format('b')})), size({WORDS.format('a')})), 0.0D)",
}


class CriteriaOf:
    """(criterion_no, criterion): the sentences of an advice, numbered from 1. A null advice has none."""

    def eval(self, advice: str) -> Iterator[tuple[int, str]]:
        said = (s.strip() for s in re.split(r"[.!?\n]+", advice or ""))
        yield from enumerate((s for s in said if len(s) >= 3), 1)


def register(spark: SparkSession, sf_dir: str) -> None:
    """Tables under their names, the views cases, criteria, judgements, registry and posts, the functions, and criteria_of."""
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
    for name, rows in (("cases", star_cases), ("criteria", star_criteria), ("judgements", star_judged), ("posts", posts)):
        rows(spark, sf_dir).createOrReplaceTempView(name)
    models(spark).createOrReplaceTempView("registry")
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("criteria_of", F.udtf(CriteriaOf, returnType="criterion_no int, criterion string"))
