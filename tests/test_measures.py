"""Boundary rules, published worked numbers and plans."""

import math

import pytest
from pyspark.sql import functions as F

from caserubric.functions import text as X
from caserubric.operators import analysis as A
from caserubric.operators import collection as C
from caserubric.operators import curation as U
from caserubric.operators import grading as G
from caserubric.operators import rubric as R
from caserubric.plans.cost import grader_calls
from caserubric.plans.oracles import ORACLES
from caserubric.plans.queries import QUERIES
from conftest import SF


def one(df):
    return df.collect()[0]


def scores(spark, rows):
    return {r["case_id"]: (r["raw"], r["score"]) for r in G.case_scores(spark.createDataFrame(rows, "model_id int, case_id int, weight int, met boolean")).collect()}


def test_score_is_clipped_and_null_without_positive_criteria(spark):
    got = scores(spark, [(0, 1, 5, True), (0, 1, 5, True), (0, 1, -8, True), (0, 2, 5, False), (0, 2, 5, False), (0, 2, -8, True), (0, 3, 5, True), (0, 4, -3, True), (0, 4, -2, False), (0, 5, 4, None)])
    assert got == {1: (0.2, 0.2), 2: (-0.8, 0.0), 3: (1.0, 1.0), 4: (None, None), 5: (0.0, 0.0)}


def test_ac1_matches_published_rows(spark):
    pairs = lambda both, a, b, none: spark.createDataFrame([(1, 1)] * both + [(1, 0)] * a + [(0, 1)] * b + [(0, 0)] * none, "a int, b int")
    assert one(A.agreement(pairs(48, 0, 1, 0), [0, 1])).ac1 == pytest.approx(0.97917, abs=1e-4)
    r = one(A.agreement(pairs(259, 21, 7, 5), [0, 1]))
    assert (r.n, round(r.ac1, 4)) == (292, 0.8908)
    same = one(A.agreement(pairs(10, 0, 0, 10), [0, 1]))
    assert (same.ac1, same.kappa) == (1.0, 1.0)


def test_pearson_p(spark):
    assert A.pearson_p(0.26, 50) == pytest.approx(0.0682, rel=2e-3)
    assert A.pearson_p(0.54, 50) == pytest.approx(5.18e-5, rel=1e-2)
    assert A.pearson_p(None, 50) is None and A.pearson_p(0.5, 2) is None
    df = spark.createDataFrame([(float(k), float(k % 3)) for k in range(30)], "x double, y double")
    assert one(A.pearson_test(df, "x", "y")).n == 30


def test_macro_f1_counts_empty_class_as_zero(spark):
    r = one(A.macro_f1(spark.createDataFrame([(1, 1), (1, 0), (1, 1)], "p int, t int"), "p", "t"))
    assert (r.f1_yes, r.f1_no, r.macro_f1) == (0.8, 0.0, 0.4)


@pytest.mark.parametrize(("s_inf", "s_align", "veto", "keep"), [(0.5, 0.9, False, False), (0.5001, 0.9, False, True), (0.9, 0.5, False, False), (0.9, 0.75, True, False)])
def test_thresholds_are_strict_and_a_veto_wins(spark, s_inf, s_align, veto, keep):
    df = spark.createDataFrame([(1, s_inf, s_align, veto)], "s_cc int, s_inf double, s_align double, vetoed boolean")
    assert one(df.select(U.keep_rule().alias("k"))).k is keep


def test_verdict_fold_and_veto(spark):
    v = spark.createDataFrame([(1, 1.0), (1, 1.0), (1, 0.0), (2, 0.5), (2, 0.5), (3, 1.0), (3, 0.5)], "thread_id int, verdict double")
    assert {r.thread_id: (round(r.s_align, 2), r.vetoed) for r in U.fold(v).collect()} == {1: (0.67, True), 2: (0.5, False), 3: (0.75, False)}


def test_text_filters(spark):
    rows = [("abc!!!",), ("",), (None,), ("<p><img src=x></p>",), ("发烧三天 怎么办",)]
    got = spark.createDataFrame(rows, "t string").select(X.symbol_share("t").alias("s"), X.text_only("t").alias("o"), X.language("t").alias("l")).collect()
    assert [r.s for r in got[:3]] == [0.5, 1.0, 1.0]
    assert [r.o for r in got] == [True, True, True, False, True]
    assert got[4].l == "zh" and got[4].s < 0.2


def test_funnel_is_monotone_and_reasons_name_every_failure(spark):
    df = spark.createDataFrame([(1, "a"), (5, None), (9, "b")], "n int, s string")
    rules = [C.Rule("small", F.col("n") < 8), C.Rule("named", F.col("s").isNotNull())]
    assert [(r.rule, r.remaining, r.removed) for r in C.filter_funnel(df, rules).collect()] == [("all", 3, 0), ("small", 2, 1), ("named", 1, 1)]
    assert [r.reasons for r in C.post_filter(df, rules).orderBy("n").collect()] == [[], ["named"], ["small"]]


def test_empty_thread_parts_are_not_forwarded_and_fabrication_is_found(spark):
    rows = [(1, 0, "user", "Severe headache since Monday."), (1, 1, "assistant", "Drink water often."), (2, 0, "user", "No reply here."), (3, 0, "assistant", "No question here."), (0, 0, "user", "Itching skin everywhere."), (0, 1, "assistant", "Apply moisturiser daily.")]
    s = U.screen(U.assemble_threads(spark.createDataFrame(rows, "thread_id long, turn long, role string, text string")))
    assert {r.thread_id: r.forwarded for r in s.collect()} == {0: False, 1: False, 2: False, 3: False}  # the only fact is the query
    more = [(t, 2, "user", f"Also fever number {t}.") for t in (0, 1)] + [(t, 3, "assistant", "Rest helps.") for t in (0, 1)]
    s = U.screen(U.assemble_threads(spark.createDataFrame(rows + more, "thread_id long, turn long, role string, text string")))
    assert {r.thread_id for r in s.where("forwarded").collect()} == {0, 1}
    assert {r.thread_id: r.supported for r in U.audit(s).collect()} == {0: True, 1: True}
    assert {r.thread_id: r.supported for r in U.audit(U.inject_fabrication(s)).collect()} == {0: False, 1: True}


def test_advice_from_the_seventh_sentence_on_is_judged_and_graded(spark):
    advice = [f"Advice{n} keeps patients{n} healthy{n}" for n in range(25)]
    rows = [(1, 0, "user", "Severe headache since Monday. Also fever today."), (1, 1, "assistant", ". ".join(advice[:10])), (1, 2, "user", "What helps against fever?"), (1, 3, "assistant", ". ".join(advice[10:]))]
    s = U.screen(U.assemble_threads(spark.createDataFrame(rows, "thread_id long, turn long, role string, text string")))
    assert one(s).advice == advice
    assert R.build_rubric(s).where("polarity = 1").count() == 25
    book = spark.createDataFrame([(7, advice[24], 1), (8, advice[0], 0)], "doc_id long, text string, toxic int")
    assert one(U.validate(s, book)).vetoed


def test_each_broken_rubric_rule_is_named(spark):
    rows = [(1, 1, "a", 1, 0), (1, 2, "b", 1, 11), (1, 3, "c", -1, -11), (1, 4, "d", 1, -5), (1, 5, "e", 1, 3), (1, 6, "e", 1, 3), (2, 1, "f", -1, -4), (3, 1, "g", 1, 10)]
    got = R.check_rubric(spark.createDataFrame(rows, "case_id int, criterion_no int, criterion string, polarity int, weight int")).collect()
    assert sorted((r.case_id, r.criterion_no or 0, r.violation) for r in got) == [(1, 1, "sign"), (1, 1, "zero"), (1, 2, "range"), (1, 3, "range"), (1, 4, "sign"), (1, 6, "duplicate"), (2, 0, "no positive")]


def test_tiers_see_what_the_former_passed(spark, monkeypatch):
    """Evidence is sought for sufficient narratives only, and only kept threads are audited."""
    talk = lambda t, user, reply: [(t, 0, "user", user), (t, 1, "assistant", reply)]
    good = "The headache is severe and it started on Monday. Severe headache with fever since Monday"
    rows = talk(1, good, "Drink much water every day. Rest in a dark room") + talk(2, "The cough and the itching. Nothing", "Drink much water every day") + talk(3, good, "Bleed the patient with leeches")
    passages = spark.createDataFrame([(7, "drink much water every single day", 0), (8, "bleed the patient with leeches now", 1)], "doc_id long, text string, toxic int")
    seen = {}
    for name, key in (("bm25", 0), ("audit", 0)):
        was = getattr(U, name)
        monkeypatch.setattr(U, name, lambda df, *x, _was=was, _name=name, **kw: (seen.setdefault(_name, sorted(r.thread_id for r in df.select("thread_id").distinct().collect())), _was(df, *x, **kw))[1])
    out = U.curate(spark.createDataFrame(rows, "thread_id long, turn long, role string, text string"), passages)
    reasons = {r.thread_id: r.reason for r in out.rejects.collect()}
    assert reasons == {2: "sufficiency", 3: "veto"} and [r.case_id for r in out.cases.collect()] == [1]
    assert seen == {"bm25": [1, 3], "audit": [1]}


@pytest.mark.parametrize("common", [0.2])
def test_bm25_is_the_same_whatever_counts_as_common(spark, common):
    words = lambda k: " ".join(f"w{(k * 7 + j * j) % (5 + j)}" for j in range(12)) + (" the" * (k % 4))
    docs = spark.createDataFrame([(k, words(k)) for k in range(60)], "doc_id long, text string")
    asked = spark.createDataFrame([(k, words(k + 3)[:20] + (" the" if k % 2 else "")) for k in range(20)] + [(99, "the"), (98, "unknown")], "q_id long, q_text string")
    rows = lambda c: sorted(map(tuple, U.bm25(asked, docs, 4, common=c).select("q_id", "doc_id", "rank", "score").collect()))
    assert rows(common) == rows(2.0)


def test_a_platform_with_a_gap_is_not_active(spark):
    weeks = {"a": (1, 8, 15), "b": (1, 8, 22), "c": (1, 8)}
    df = spark.createDataFrame([(p, f"2024-01-{day:02d}") for p, days in weeks.items() for day in days], "platform string, day string").withColumn("ts", F.to_timestamp("day"))
    assert {r.platform: (r.active_weeks, r.ok) for r in C.weekly_activity(df, "platform", "ts", 3).collect()} == {"a": (3, True), "b": (3, False), "c": (2, False)}


def test_rouge_l_and_bleu(spark):
    p = spark.createDataFrame([("same", "a b c d e", "a b c d e"), ("half", "a x c y", "a b c d"), ("none", "", "a b")], "id string, candidate string, reference string")
    assert {r.id: r.f for r in G.rouge_l(p).collect()} == {"same": 1.0, "half": 0.5, "none": 0.0}
    b = {r.id: r.bleu for r in G.bleu(p).collect()}
    assert b["same"] == 1.0 and b["none"] == 0.0 and 0 < b["half"] < 1


def test_recovery_is_guarded(spark):
    df = spark.createDataFrame([(1, 25.61, 24.54, 25.21), (2, 10.0, 11.0, 12.0)], "model_id int, baseline double, closed double, open double")
    got = {r.model_id: (r.gain, r.recovery) for r in A.recovery(df).collect()}
    assert got[1][0] == 0.67 and got[1][1] == pytest.approx(0.626, abs=1e-3) and got[2] == (1.0, None)


def test_grader_calls():
    assert grader_calls(16702, 38) == 634_676


def test_case_scores_need_one_exchange_on_the_case(spark):
    plan = G.case_scores(QUERIES["rubric_star"].__globals__["star_judged"](spark, SF))._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    assert plan.count("hashpartitioning(case_id") + plan.count("hashpartitioning(l_orderkey") <= 2


def test_pairs_and_alignment_take_all_models(spark, monkeypatch):
    rows = QUERIES["pairwise_wins"](spark, SF).collect()
    assert len({(r.a, r.b) for r in rows}) == len(rows) == 38 * 37 // 2
    judged = spark.createDataFrame([(m, c, 1, 1, m == 37) for m in (3, 37) for c in range(11)], "model_id int, case_id long, criterion_no int, weight int, met boolean")
    monkeypatch.setitem(QUERIES["grader_alignment"].__globals__, "star_judged", lambda spark, d: judged)
    assert all(0 < r.macro_f1 for r in QUERIES["grader_alignment"](spark, SF).collect())
    met = {r.pair: r.macro_f1 for r in QUERIES["grader_alignment"](spark, SF).collect()}
    # 22 judgements, 11 of each kind, and each physician flips one of either kind: 10 of 11 right in both classes
    assert met["grader 1"] == met["grader 2"] == pytest.approx(10 / 11, abs=1e-6)


def test_every_oracle_has_a_query_and_the_flagship_runs(spark):
    assert set(ORACLES) <= set(QUERIES)
    rows = QUERIES["leaderboard"](spark, SF).collect()
    assert len(rows) == 38 and not any(math.isnan(r.score) for r in rows)


def test_near_pairs_against_brute_force(spark):
    base = [f"w{k}" for k in range(60)]
    texts = {0: base, 1: base[:-2] + ["x", "y"], 2: [f"v{k}" for k in range(60)], 3: base}
    df = spark.createDataFrame([(k, " ".join(v)) for k, v in texts.items()], "doc_id int, text string")
    got = {(r.a, r.b): round(r.jaccard, 4) for r in C.near_pairs(df, "doc_id", "text").collect()}
    sets = {k: {tuple(v[i : i + 5]) for i in range(56)} for k, v in texts.items()}
    assert got == {(0, 1): round(len(sets[0] & sets[1]) / len(sets[0] | sets[1]), 4)}


def test_dedup_near_names_every_exact_copy(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").toPandas()
    first = docs.groupby("text", dropna=False).doc_id.transform("min")
    copies = set(zip(first[first < docs.doc_id], docs.doc_id[first < docs.doc_id]))
    got = {(r.a, r.b) for r in QUERIES["dedup_near"](spark, SF).collect() if r.jaccard == 1}
    assert copies and copies <= got
    odd = spark.createDataFrame([(3, "x"), (1, "x"), (1, "x"), (5, None), (4, None), (7, "y")], "doc_id long, text string")
    assert {tuple(r) for r in C.copy_pairs(odd, "doc_id", "text").collect()} == {(1, 3, 1.0), (4, 5, 1.0)}


def test_ann_recall(spark):
    r = one(QUERIES["ann_recall"](spark, SF))
    assert r.wanted == 250 and r.recall >= 0.9
