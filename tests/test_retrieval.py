import math
import random

import numpy as np
from pyspark.sql import functions as F

from caserubric.operators import curation as U
from caserubric.operators import dense, sparse
from caserubric.shared import placed


def brute(asked, docs, k):
    """The k best by adding up every contribution of every term."""
    toks = {i: t.lower().split() for i, t in docs}
    n, mean = len(docs), sum(map(len, toks.values())) / len(docs)
    df = {}
    for t in toks.values():
        for x in set(t):
            df[x] = df.get(x, 0) + 1
    out = []
    for q, text in asked:
        terms, scores = set(text.lower().split()), {}
        for i, t in toks.items():
            for x in terms & set(t):
                idf, c = math.log(1 + (n - df[x] + 0.5) / (df[x] + 0.5)), t.count(x)
                scores[i] = scores.get(i, 0) + math.floor(idf * (c * 2.2 / (c + 1.2 * (0.25 + 0.75 * len(t) / mean))) * 1000 + 0.5)
        best = sorted(scores.items(), key=lambda x: (-x[1], x[0]))[:k]
        out += [(q, i, r + 1, s, len({x for x in terms & set(toks[i]) if len(x) >= 4})) for r, (i, s) in enumerate(best)]
    return sorted(out)


def test_shards_and_slices_give_what_one_pass_gives(spark, monkeypatch):
    rng = random.Random(5)
    words = ["the", "of", *(f"word{i}" for i in range(40))]
    docs = [(i, " ".join(["all"] + rng.choices(words, [20, 20] + [1] * 40, k=rng.randint(0, 30)))) for i in range(90)]
    asked = [(i, " ".join(rng.choices(words, k=5))) for i in range(60)] + [(100, "all"), (101, "unknown"), (102, "")]
    monkeypatch.setattr(sparse, "SHARD_POSTINGS", 300)
    monkeypatch.setattr(sparse, "SLICE_QUERIES", 30)
    hits = U.bm25(spark.createDataFrame(asked, "q_id long, q_text string"), spark.createDataFrame(docs, "doc_id long, text string"), 4, qid=["q_id"])
    assert sorted(map(tuple, hits.select("q_id", "doc_id", "rank", "score", "shared").collect())) == brute(asked, docs, 4)
    assert "Join" not in hits._jdf.queryExecution().simpleString()


def test_each_cell_has_a_partition_of_its_own(spark):
    rows = spark.createDataFrame([(x,) for x in placed(spark, 15)], "place long").repartition(15, "place")
    assert rows.select(F.spark_partition_id().alias("p")).distinct().count() == 15


def test_verdicts_by_counts_are_those_by_passages(spark):
    p = spark.createDataFrame([(1, "take aspirin with water daily", 0), (2, "never take aspirin daily with water", 1), (3, "other matters", 0)], "doc_id long, text string, toxic int")
    advice = spark.createDataFrame([(7, 0, "take aspirin daily"), (7, 1, "other things happen"), (8, 0, "an ox"), (9, 0, "sleep")], "thread_id long, advice_no int, advice_text string")
    hits = U.bm25(advice, p, 1, qid=["thread_id", "advice_no"], qtext="advice_text")
    by_counts = U.verdicts(advice, hits, p)
    assert sorted(map(tuple, by_counts.collect())) == sorted(map(tuple, U.verdicts(advice, hits.drop("shared"), p).collect()))
    assert "array_intersect" not in by_counts._jdf.queryExecution().optimizedPlan().toString()


def test_more_queries_than_a_block_and_many_copies(spark, monkeypatch):
    rng = np.random.default_rng(2)
    v = rng.normal(size=(70, 8)).astype(np.float32)
    v[20:50] = v[20]  # copies, whose ties fall to the smallest ids
    monkeypatch.setattr(dense, "BLOCK_QUERIES", 10)
    monkeypatch.setattr(dense, "TILE", 16)
    monkeypatch.setattr(dense, "HELD", 40)
    rows = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "id long, x array<float>")
    asked, corpus = rows.select(F.col("id").alias("q_id"), F.col("x").alias("q")), rows.select(F.col("id").alias("doc_id"), F.col("x").alias("v")).repartition(3)
    w = v.astype(float)
    want = []
    for i in range(70):
        near = sorted(((-round(float(w[i] @ w[j]), 6), j) for j in range(70) if j != i))[:5]
        want += [(i, j, r + 1) for r, (_, j) in enumerate(near)]
    hits = D_rows(dense.exact_top_k(asked, corpus, 5))
    assert hits == sorted(want)
    assert D_rows(dense.lsh_top_k(asked, corpus, 5, planes=0, tables=1, dim=8)) == hits  # no plane: all agree


def D_rows(hits):
    return sorted(map(tuple, hits.select("q_id", "doc_id", "rank").collect()))


def test_hyperplanes_find_what_the_join_on_signs_finds(spark):
    rng = np.random.default_rng(4)
    v = rng.normal(size=(60, 8))
    rows = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "id long, x array<double>")
    bits = np.einsum("tpd,nd->ntp", dense.hyperplanes(3, 4, 8), v) > 0
    want = []
    for i in range(60):
        met = [j for j in range(60) if j != i and (bits[i] == bits[j]).all(axis=1).any()]
        want += [(i, j, r + 1) for r, (_, j) in enumerate(sorted((-round(float(v[i] @ v[j]), 6), j) for j in met)[:5])]
    hits = dense.lsh_top_k(rows.select(F.col("id").alias("q_id"), F.col("x").alias("q")), rows.select(F.col("id").alias("doc_id"), F.col("x").alias("v")), 5, tables=3, dim=8)
    assert D_rows(hits) == sorted(want)
    assert "Join" not in hits._jdf.queryExecution().simpleString()
