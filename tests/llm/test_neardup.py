"""Near duplicates: names that clash, hot classes, extra columns, long texts."""

import random

import pyarrow as pa
from pyspark.sql import functions as F

from caserubric.llm import neardup
from caserubric.llm.common import join_facts
from caserubric.llm.neardup import Overlap, near_duplicates, one_of_each


def few_names(make):
    """describe with three names for all classes; their tags still differ."""

    def wrapped(rule):
        run = make(rule)

        def some(batches):
            for out in run(batches):
                names = [None if x is None else x % 3 for x in out.column("name").to_pylist()]
                yield out.set_column(3, "name", pa.array(names, pa.int64()))

        return some

    return wrapped


def family(rng, tag, size, changes):
    base = [f"{tag}{rng.randrange(900)}" for _ in range(size)]
    return " ".join(base), " ".join(f"x{rng.random()}" if k < changes else w for k, w in enumerate(base))


def test_classes_of_one_name_are_told_apart(spark, monkeypatch):
    rng = random.Random(2)
    docs = [(10 * k + j, t) for k in range(12) for j, t in enumerate(family(rng, f"f{k}w", 80, 2 if k % 2 else 60))]
    docs += [(500 + k, docs[0][1]) for k in range(5)]
    frame = spark.createDataFrame(docs, "doc_id long, text string")
    want = sorted(map(tuple, near_duplicates(frame, Overlap(4, 85, 100)).select("doc_id", "n_shingles", "component_id").collect()))
    assert [c for i, _, c in want if i in (10, 11, 20, 21, 504)] == [10, 10, 20, 21, 0]
    monkeypatch.setattr(neardup, "describe", few_names(neardup.describe))
    assert sorted(map(tuple, near_duplicates(frame, Overlap(4, 85, 100)).select("doc_id", "n_shingles", "component_id").collect())) == want


def test_long_texts_and_any_column_names(spark):
    rng = random.Random(5)
    a, b = family(rng, "w", 40_000, 300)
    rows = [(1, a, 1), (2, b, 2), (3, "", 3), (4, None, 4), (None, a, 5), (5, "A b c", 6), (6, "a B c", 7), (7, "Ä b c", 8), (8, "ä b c", 9), (1, a, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, k1 int").withColumns({c: F.lit(c) for c in ("row", "k2", "name", "_key", "key", "_hot", "group", "a.b")})
    got = {(r.doc_id, r.component_id) for r in near_duplicates(docs).collect()}
    assert got == {(1, 1), (2, 1), (3, 3), (4, 4), (None, 1), (5, 5), (6, 5), (7, 7), (8, 8)}
    kept = one_of_each(docs)
    assert kept.columns == docs.columns
    assert sorted((r["doc_id"], r["k1"], r["_key"]) for r in kept.collect()) == [(1, 1, "_key"), (3, 3, "_key"), (4, 4, "_key"), (5, 6, "_key"), (7, 8, "_key"), (8, 9, "_key")]


def test_facts_join_hot_rare_missing_and_null_keys(spark):
    rows = spark.createDataFrame([(k, "hot" if k % 3 else None if k % 2 else f"r{k}") for k in range(60)], "id long, key string")
    facts = rows.where("key is not null and key <> 'r9'").groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("least"))
    for share in (1, 4, 10_000):
        got = {(r.id, r.least) for r in join_facts(rows, facts, "key", ["id"], share).collect()}
        assert got == {(k, 1 if k % 3 else None if k % 2 or False else k) if k != 9 else (9, None) for k in range(60)}
