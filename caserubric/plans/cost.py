"""Counts of agent calls, with and without the cascade, and the order of predicates."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as X
from ..operators.collection import Rule

#: Tier of each stage of the funnel: the agent that decides it and its size in billions of parameters.
TIERS = {"screen": ("screener", 4), "complaint": ("validator", 120), "sufficiency": ("validator", 120), "veto": ("validator", 120), "alignment": ("validator", 120), "audit": ("controller", 4)}


def cost_report(funnel: DataFrame) -> DataFrame:
    """stage, agent, params_b, calls in the cascade, and flat_calls if every thread went to every agent."""
    before = F.lag("remaining").over(Window.orderBy("step"))
    total = F.max("remaining").over(Window.partitionBy())
    named = F.create_map(*[F.lit(x) for k, (a, _) in TIERS.items() for x in (k, a)])
    size = F.create_map(*[F.lit(x) for k, (_, b) in TIERS.items() for x in (k, b)])
    out = funnel.withColumn("calls", before).withColumn("flat_calls", total).where("step > 0")
    return out.select("stage", F.element_at(named, F.col("stage")).alias("agent"), F.element_at(size, F.col("stage")).alias("params_b"), "calls", "flat_calls")


def token_report(screened: DataFrame, rejects: DataFrame) -> DataFrame:
    """stage, calls, tokens of the threads that reach each stage, and flat_tokens if every thread went to every stage."""
    at = F.create_map(*[F.lit(x) for i, k in enumerate(TIERS) for x in (k, i)])
    place = F.coalesce(F.element_at(at, F.col("reason")), F.lit(len(TIERS)))
    rows = screened.select("thread_id", F.size(X.tokens("thread_text")).cast("long").alias("n")).join(rejects, "thread_id", "left").withColumn("place", place)
    sums = [f(F.when(place >= i, x)).alias(f"{name}{i}") for i in range(len(TIERS)) for f, x, name in ((F.count, F.lit(1), "c"), (F.sum, F.col("n"), "t"))]
    cells = [F.struct(F.lit(k).alias("stage"), F.col(f"c{i}").alias("calls"), F.coalesce(f"t{i}", F.lit(0)).alias("tokens"), F.coalesce("t0", F.lit(0)).alias("flat_tokens")) for i, k in enumerate(TIERS)]
    return rows.agg(*sums).select(F.inline(F.array(*cells)))


def plan_cost(df: DataFrame) -> dict[str, int]:
    """Scans, shuffles, broadcasts and Python steps of the plan of df, before it runs; a shuffle that is used again counts once."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    count = lambda *names: sum(len(re.findall(rf"(?m)^\W*(?:\(\d+\) )?{n}\b", plan)) for n in names)
    return {"scans": count("FileScan", "Scan", "BatchScan"), "shuffles": count("Exchange"), "broadcasts": count("BroadcastExchange"), "python": count("MapInPandas", "MapInArrow", "ArrowEvalPython", "BatchEvalPython", "FlatMapGroupsInPandas", "FlatMapGroupsInArrow")}


def grader_calls(criteria: int, models: int, per_request: int = 1) -> int:
    """Judgements for a set of criteria and models; several criteria of one answer may share a request."""
    return -(-criteria // per_request) * models


def order_rules(rows: DataFrame, rules: list[tuple[Rule, float]], sample: float = 0.01, seed: int = 1) -> list[Rule]:
    """Rules by cost over the share that they remove, measured on a sample: cheap and selective ones first."""
    tests = [F.avg((~F.coalesce(r.test, F.lit(False))).cast("double")).alias(f"r{k}") for k, (r, _) in enumerate(rules)]
    seen = rows.sample(fraction=sample, seed=seed).agg(*tests).first()
    rank = {k: cost / max(1e-9, seen[f"r{k}"] or 0.0) for k, (_, cost) in enumerate(rules)}
    return [rules[k][0] for k in sorted(rank, key=rank.get)]
