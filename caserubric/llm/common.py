"""Shared pieces: the word pattern, published tables, connected components."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shared import fresh_path, publish, shared_dir  # noqa: F401

#: A word is a run of characters other than the ASCII blanks.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(text: Column) -> Column:
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(WORD), F.lit(0))


def join_facts(rows: DataFrame, facts: DataFrame, key: str, spread: list[str], share: int = 1000) -> DataFrame:
    """rows left-joined with facts, one row a key whose column n counts the key's rows; n is dropped.

    Any key may hold most of the rows. Keys with one row in `share` or more are `share` at most, whatever the data, so their
    facts are broadcast; their rows, and those of a null key, are spread by the columns `spread` for the join of the others.
    """
    total = facts.agg(F.sum("n")).first()[0] or 0
    names = [c for c in facts.columns if c not in (key, "n")]
    hot = facts.where(F.col("n") * share >= total).select(F.col(key).alias("_hot"), F.struct(*names).alias("_hot_facts"))
    rest = facts.where(F.col("n") * share < total).select(F.col(key).alias("_key"), F.struct(*names).alias("_facts"), F.lit(0).cast("long").alias("_place"))
    out = rows.join(F.broadcast(hot), F.col(key) == F.col("_hot"), "left")
    out = out.withColumn("_salt", F.when(F.col("_hot").isNotNull() | F.col(key).isNull(), 1 + F.pmod(F.xxhash64(*spread), F.lit(1024))).otherwise(F.lit(0)).cast("long"))
    out = out.join(rest, (F.col(key) == F.col("_key")) & (F.col("_salt") == F.col("_place")), "left")
    return out.select(*[F.col(c) for c in rows.columns], *[F.coalesce(F.col(f"_hot_facts.{c}"), F.col(f"_facts.{c}")).alias(c) for c in names])


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(id, component) of every id in edges; component is the smallest id reachable.

    Alternates large-star and small-star steps, each one shuffle with map-side minima, until the edges are stars.
    Rounds grow with the logarithm of the longest path. Null ends and self loops are ignored; no edges, no rows.
    """
    pairs = edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).distinct()
    pairs = publish(pairs, "edges")
    while True:
        both = pairs.union(pairs.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))
        low = both.groupBy("hi").agg(F.min("lo").alias("m")).select(F.col("hi").alias("node"), F.least("hi", "m").alias("m"))
        # large star: every larger neighbour of a node points at the smallest of the neighbourhood
        large = pairs.join(low, pairs.lo == low.node).select("hi", F.col("m").alias("lo"))
        large = publish(large.where("hi <> lo").distinct(), "large")
        # small star: a node and its smaller neighbours point at the smallest of them
        best = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(best, "hi").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).where("hi <> lo")
        after = publish(small.union(best.select("hi", F.col("m").alias("lo"))).distinct(), "small")
        changed = after.join(pairs, ["hi", "lo"], "left_anti").limit(1).count() or pairs.join(after, ["hi", "lo"], "left_anti").limit(1).count()
        pairs = after
        if not changed:
            break
    roots = pairs.select(F.col("lo").alias("id")).distinct()
    return pairs.select(F.col("hi").alias("id"), F.col("lo").alias("component")).union(roots.select("id", F.col("id").alias("component")))
