"""Agents with their cache, the SQL surface, and the cost of plans."""

import pandas as pd
from pyspark.sql import functions as F

from caserubric.operators import agents as G
from caserubric.operators import analysis as A
from caserubric.operators import collection as C
from caserubric.operators import curation as U
from caserubric.operators import grading
from caserubric.plans import sql
from caserubric.plans.cost import plan_cost
from caserubric.tables import models
from conftest import SF


def test_equal_prompts_are_asked_once_and_answers_are_kept(spark, tmp_path):
    def echo(prompts: pd.Series) -> pd.Series:
        if prompts.duplicated().any() or prompts.str.contains("old").any() and (tmp_path / "asked").exists():
            raise ValueError("asked again")
        return prompts.str.upper()

    cache, agent = str(tmp_path / "cache"), G.Agent("echo", 1, echo)
    first = spark.createDataFrame([(1, "old a"), (2, "old a"), (3, None)], "id int, prompt string").coalesce(1)
    assert sorted(map(tuple, G.ask(first, agent, cache).select("id", "answer").collect())) == [(1, "OLD A"), (2, "OLD A"), (3, "")]
    (tmp_path / "asked").touch()
    more = first.union(spark.createDataFrame([(4, "b")], "id int, prompt string"))
    got = G.ask(more, agent, cache)
    assert got.columns == ["id", "prompt", "answer"] and {r.id: r.answer for r in got.collect()} == {1: "OLD A", 2: "OLD A", 3: "", 4: "B"}
    assert spark.read.parquet(cache).count() == 3
    assert G.ask(first.limit(0), agent, cache).count() == 0


def test_the_grading_agent_judges_as_the_rule_does(spark, tmp_path):
    rubric = spark.createDataFrame([(1, 1, "Drink enough water daily", 5), (1, 2, "Smoke heavily", -5), (1, 3, "No", 1)], "case_id long, criterion_no int, criterion string, weight int")
    answers = spark.createDataFrame([("m", 1, "You should drink enough clean water daily."), ("n", 1, None)], "model string, case_id long, text string")
    asked = rubric.join(answers, "case_id").withColumn("prompt", G.claim_prompt(F.col("criterion"), F.col("text")))
    got = {(r.model, r.criterion_no): r.answer == "1" for r in G.ask(asked, G.GRADER, str(tmp_path / "c")).collect()}
    want = {(r.model, r.criterion_no): bool(r.met) for r in grading.grade(answers, rubric).collect()}
    assert got == want and got["m", 1] and not got["n", 1]


def test_each_agent_keeps_answers_of_its_own(spark, tmp_path):
    rows = spark.createDataFrame([(1, '{"claim": "fever rises fast", "ground": "high fever"}')], "id int, prompt string")
    got = [G.ask(rows, a, str(tmp_path / "c")).first().answer for a in (G.VALIDATOR, G.CONTROLLER, G.SCREENER)]
    assert got == ["0", "0", "0"]
    assert G.VALIDATOR.answer(pd.Series(['{"claim": "fever rises", "ground": "the fever"}'])).tolist() == ["1"]


def test_sql_surface(spark):
    sql.register(spark, SF)
    r = spark.sql("SELECT clip01(1.5D) a, clip01(-1D) b, clip01(CAST(NULL AS DOUBLE)) c, coverage('alpha beta', 'Alpha, gamma!') d, coverage('', 'x') e, content_words('Über the große') f").first()
    assert (r.a, r.b, r.c, r.d, r.e, sorted(r.f)) == (1.0, 0.0, None, 0.5, 0.0, ["große", "über"])
    assert [tuple(x) for x in spark.sql("SELECT * FROM criteria_of('Rest well. Drink!\\nNo')").collect()] == [(1, "Rest well"), (2, "Drink")]
    said = spark.sql("SELECT conv_id, criterion FROM conversations, LATERAL criteria_of(text) WHERE role = 'assistant'")
    assert said.count() > 0
    board = spark.sql("SELECT model_id, avg(clip01(got / possible)) AS score FROM (SELECT model_id, case_id, sum(CASE WHEN met THEN weight ELSE 0 END) AS got, sum(CASE WHEN weight > 0 THEN weight ELSE 0 END) AS possible FROM judgements GROUP BY ALL) WHERE possible > 0 GROUP BY model_id")
    want = grading.leaderboard(grading.case_scores(spark.table("judgements")))
    assert {r.model_id: round(r.score, 6) for r in board.collect()} == {r.model_id: r.score for r in want.collect()}


def test_plan_cost_counts_scans_and_shuffles(spark):
    orders = spark.read.parquet(f"{SF}/orders.parquet")
    assert plan_cost(orders.select("o_orderkey"))["shuffles"] == 0
    cost = plan_cost(orders.groupBy("o_orderpriority").count())
    assert (cost["scans"], cost["shuffles"], cost["python"]) == (1, 1, 0)


def test_bootstrap_finds_a_planted_drop_and_no_other(spark):
    cases = spark.range(6000).select(F.col("id").alias("case_id"), F.date_add(F.lit("1995-01-01").cast("date"), (F.col("id") % 3650).cast("int")).alias("published"))
    reg = models(spark).where("model_id < 2")
    luck = F.pmod(F.xxhash64("case_id", "model_id"), F.lit(1000)) / 1000.0
    s = cases.crossJoin(reg.select("model_id", F.coalesce("cutoff", "released").alias("eff"))).withColumn("score", luck - F.when((F.col("model_id") == 0) & (F.col("published") > F.col("eff")), 0.3).otherwise(0.0)).drop("eff")
    got = {r.model_id: r for r in A.drop_bootstrap(s, reg).collect()}
    assert got[0].high < 0 and got[0].p == 0 and got[1].low < 0.02 and got[1].high > -0.02 and got[1].low <= got[1].mid <= got[1].high
    assert A.drop_bootstrap(s, reg).collect() == A.drop_bootstrap(s, reg).collect()


def test_no_rows_give_no_bootstrap(spark):
    none = spark.createDataFrame([], "model_id int, case_id long, score double, published date")
    assert A.drop_bootstrap(none, models(spark)).count() == 0


def test_correlation_without_variance_is_null(spark):
    s = spark.createDataFrame([(0, 1, 0.5), (1, 1, 0.5), (0, 2, 0.5), (1, 2, 0.7), (0, 3, None), (1, 3, 0.1)], "model_id int, case_id int, score double")
    r = A.pearson_pairs(s).first()
    assert (r.a, r.b, r.n, r.r, r.t) == (0, 1, 2, None, None)
    flat = spark.createDataFrame([(1.0, 2.0), (1.0, 3.0), (1.0, 5.0), (None, 9.0)], "x double, y double")
    assert tuple(A.pearson_test(flat, "x", "y").first()) == (3, None, None)
    line = spark.createDataFrame([(1.0, 2.0), (2.0, 4.0), (3.0, 6.0), (9.0, None)], "x double, y double")
    r = A.pearson_test(line, "x", "y").first()
    assert (r.n, r.r) == (3, 1.0) and r.p < 1e-6


def test_approximate_head_count_is_near_the_exact_one(spark):
    seen = spark.range(20000).select((F.col("id") % 3).alias("platform"), (F.col("id") % 6001).alias("author"))
    exact = {r.platform: r.n_verified for r in C.verified_count(seen, "platform", "author", 10).collect()}
    rough = {r.platform: r.n_verified for r in C.verified_count(seen, "platform", "author", 10, approx=True).collect()}
    assert exact.keys() == rough.keys() and all(abs(rough[k] - n) <= 0.1 * n for k, n in exact.items())


def test_a_week_holds_its_first_instant_and_not_the_next_week(spark):
    rows = spark.createDataFrame([(1, "2024-01-08 00:00:00"), (2, "2024-01-14 23:59:59"), (3, "2024-01-15 00:00:00"), (4, "2024-01-07 23:59:59"), (5, None)], "id int, t string").select("id", F.col("t").cast("timestamp").alias("posted_at"))
    assert sorted((r.id, str(r.harvest_week)) for r in C.harvest_week(rows, "2024-01-08").collect()) == [(1, "2024-01-08"), (2, "2024-01-08")]


def test_lists_of_several_sources_are_fused_by_rank(spark):
    docs = spark.createDataFrame([(1, "rest and water"), (2, "rest"), (3, "water water"), (4, None)], "doc_id long, text string")
    asked = spark.createDataFrame([(1, "water rest"), (2, "none"), (3, None)], "q_id long, q_text string")
    hits = U.per_source(asked, {"odd": docs.where("doc_id % 2 = 1"), "even": docs.where("doc_id % 2 = 0"), "all": docs}, 2, qid=["q_id"])
    assert {r.source for r in hits.collect()} == {"odd", "even", "all"} and {r.q_id for r in hits.collect()} == {1}
    best = U.fuse_ranks([hits], ["q_id"], 1).first()
    assert best.doc_id == 1 and abs(best.score - 2 / 61) < 1e-8


def test_requirements_add_up_to_the_sufficiency(spark):
    rows = spark.createDataFrame([(1, "does fever harm", ["Fevers since monday"], True), (2, "does fever harm", ["no"], False)], "thread_id int, query string, facts array<string>, forwarded boolean")
    got = {r.requirement: r.met for r in U.requirements(rows).collect()}
    assert got == {"does": False, "fever": True, "harm": False}
    assert abs(rows.select(U.sufficiency(F.col("query"), F.col("facts")).alias("s")).first().s - 1 / 3) < 1e-9
