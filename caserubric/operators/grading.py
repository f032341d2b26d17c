"""Grading, case scores, leaderboards, and lexical and holistic baselines."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from ..functions import text as X


def grade(responses: DataFrame, rubric: DataFrame, tau: float = 0.8, keys: tuple[str, ...] = ("model",)) -> DataFrame:
    """Judged rows: a criterion is met if the answer covers it. One join on the case, one judgement for each row."""
    r = responses.select("case_id", *keys, X.content("text").alias("rc"))
    j = rubric.withColumn("cc", X.content("criterion")).join(r, "case_id")
    return j.withColumn("met", X.coverage_of(F.col("cc"), F.col("rc")) >= tau).drop("cc", "rc")


def grade_with_agent(responses: DataFrame, rubric: DataFrame, agent, schema: str) -> DataFrame:
    """The same by an agent that maps batches of pandas frames, where a model endpoint would plug in."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        return agent(frames)

    return rubric.join(responses, "case_id").mapInPandas(run, schema)


def case_scores(judged: DataFrame, model: str = "model_id") -> DataFrame:
    """model, case_id, got, possible, raw, score: met weights over positive weights, clipped to [0, 1].

    Without a positive criterion raw and score are null; the clip is guarded, as least() and greatest() skip nulls. A null
    judgement counts as not met.
    """
    met, w = F.coalesce("met", F.lit(False)), F.col("weight")
    out = judged.groupBy("case_id", model).agg(F.sum(F.when(met, w).otherwise(0)).cast("long").alias("got"), F.sum(F.when(w > 0, w).otherwise(0)).cast("long").alias("possible"))
    raw = F.when(F.col("possible") > 0, F.col("got") / F.col("possible"))
    return out.withColumn("raw", raw).withColumn("score", F.when(F.col("raw").isNotNull(), F.least(F.greatest(F.col("raw"), F.lit(0.0)), F.lit(1.0))))


def leaderboard(scores: DataFrame, model: str = "model_id") -> DataFrame:
    """model, score, n_cases, n_excluded, rank: the mean over cases that have a score."""
    out = scores.groupBy(model).agg(F.round(F.avg("score"), 6).alias("score"), F.count("score").alias("n_cases"), F.sum(F.col("score").isNull().cast("long")).alias("n_excluded"))
    return out.withColumn("rank", F.rank().over(Window.orderBy(F.col("score").desc())).cast("long"))


def leaderboard_modes(judged: DataFrame, model: str = "model_id") -> DataFrame:
    """model, micro, unweighted, positive, critical from one pass over the judgements."""
    met, w = F.coalesce("met", F.lit(False)), F.col("weight")
    ratio = lambda a, b: F.round(F.sum(F.when(a, 1).otherwise(0)) / F.sum(F.when(b, 1).otherwise(0)), 6)
    micro = F.round(F.sum(F.when(met, w).otherwise(0)) / F.sum(F.when(w > 0, w).otherwise(0)), 6)
    return judged.groupBy(model).agg(micro.alias("micro"), F.round(F.avg(met.cast("double")), 6).alias("unweighted"), ratio(met & (w > 0), w > 0).alias("positive"), ratio(met & (F.abs(w) == 10), F.abs(w) == 10).alias("critical"))


def axis_scores(judged: DataFrame, model: str = "model_id") -> DataFrame:
    met, w = F.coalesce("met", F.lit(False)), F.col("weight")
    return judged.groupBy(model, "axis").agg(F.round(F.sum(F.when(met, w).otherwise(0)) / F.nullif(F.sum(F.when(w > 0, w).otherwise(0)), F.lit(0)), 6).alias("score"))


def holistic_score(text: Column) -> Column:
    """Stand-in for a judge that gives one overall grade: it rises with the logarithm of the length and is skewed high."""
    return F.least(F.lit(1.0), F.lit(0.55) + F.log(F.lit(1.0) + F.length(text)) / 20)


def pairwise_wins(scores: DataFrame, model: str = "model_id") -> DataFrame:
    """a, b, wins, losses, ties over common cases. Scores of a case meet as one array, whose length is the number of models."""
    rows = scores.where("score is not null").groupBy("case_id").agg(F.sort_array(F.collect_list(F.struct(F.col(model).alias("m"), "score"))).alias("s"))
    pair = rows.select(F.explode("s").alias("x"), "s").select("x", F.explode(F.filter("s", lambda y: y["m"] > F.col("x.m"))).alias("y"))
    beat = lambda c: F.sum(c.cast("long"))
    return pair.groupBy(F.col("x.m").alias("a"), F.col("y.m").alias("b")).agg(beat(F.col("x.score") > F.col("y.score")).alias("wins"), beat(F.col("x.score") < F.col("y.score")).alias("losses"), beat(F.col("x.score") == F.col("y.score")).alias("ties"))


def ngram_overlap_counts(pairs: DataFrame, n: int) -> DataFrame:
    """id, hits (clipped), in_candidate, in_reference for n-grams of pairs (id, candidate, reference)."""
    grams = lambda c: X.ngrams(X.tokens(c), n)
    size = lambda c: F.greatest(F.size(X.tokens(c)) - (n - 1), F.lit(0)).cast("long")
    total = pairs.select("id", size("candidate").alias("in_candidate"), size("reference").alias("in_reference"))
    side = lambda c, name: pairs.select("id", F.explode(grams(c)).alias("g")).groupBy("id", "g").agg(F.count(F.lit(1)).alias(name))
    hits = side("candidate", "a").join(side("reference", "b"), ["id", "g"]).groupBy("id").agg(F.sum(F.least("a", "b")).alias("hits"))
    return total.join(hits, "id", "left").select("id", F.coalesce("hits", F.lit(0)).cast("long").alias("hits"), "in_candidate", "in_reference")


def prf(hits: Column, cand: Column, ref: Column) -> list[Column]:
    p = F.when(cand > 0, hits / cand).otherwise(F.lit(0.0))
    r = F.when(ref > 0, hits / ref).otherwise(F.lit(0.0))
    return [F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(F.when(p + r > 0, 2 * p * r / (p + r)).otherwise(F.lit(0.0)), 6).alias("f")]


def rouge_n(pairs: DataFrame, n: int) -> DataFrame:
    return ngram_overlap_counts(pairs, n).select("id", *prf(F.col("hits"), F.col("in_candidate"), F.col("in_reference")))


@F.pandas_udf(LongType())
def lcs_length(a: pd.Series, b: pd.Series) -> pd.Series:
    """Longest common subsequence of token arrays, a row of the table as one bit string."""
    out = []
    for x, y in zip(a, b, strict=True):
        masks: dict[str, int] = {}
        for k, w in enumerate(x if x is not None else ()):
            masks[w] = masks.get(w, 0) | 1 << k
        full = (1 << len(x if x is not None else ())) - 1
        row = full
        for w in y if y is not None else ():
            u = row & masks.get(w, 0)
            row = (row + u | row - u) & full
        out.append(full.bit_count() - row.bit_count())
    return pd.Series(out)


def rouge_l(pairs: DataFrame) -> DataFrame:
    t = pairs.select("id", X.tokens("candidate").alias("c"), X.tokens("reference").alias("r"))
    return t.withColumn("hits", lcs_length("c", "r")).select("id", *prf(F.col("hits"), F.size("c"), F.size("r")))


def bleu(pairs: DataFrame, max_n: int = 4, smooth: bool = True) -> DataFrame:
    """id, bleu: geometric mean of clipped precisions with brevity penalty; add-one smoothing above unigrams."""
    out = None
    for n in range(1, max_n + 1):
        c = ngram_overlap_counts(pairs, n)
        add = F.lit(1 if smooth and n > 1 else 0)
        num, den = F.col("hits") + add, F.col("in_candidate") + add
        part = c.select("id", F.when((num > 0) & (den > 0), F.log(num / den)).alias(f"l{n}"), *([F.col("in_candidate").alias("c"), F.col("in_reference").alias("r")] if n == 1 else []))
        out = part if out is None else out.join(part, "id")
    mean = sum((F.col(f"l{n}") for n in range(1, max_n + 1)), F.lit(0.0)) / max_n
    penalty = F.when(F.col("c") >= F.col("r"), F.lit(1.0)).when(F.col("c") == 0, F.lit(0.0)).otherwise(F.exp(1 - F.col("r") / F.col("c")))
    return out.select("id", F.round(F.coalesce(penalty * F.exp(mean), F.lit(0.0)), 6).alias("bleu"))


def choice_accuracy(answers: DataFrame, key: DataFrame, model: str = "model_id") -> DataFrame:
    """model, n, accuracy of answers (model, item_id, choice) against key (item_id, right)."""
    return answers.join(key, "item_id").groupBy(model).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("choice") == F.col("right")).cast("double")), 6).alias("accuracy"))


def check_runs(responses: DataFrame, keys: tuple[str, ...] = ("model_id", "case_id", "mode")) -> DataFrame:
    """Keys that were answered more than once."""
    return responses.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).where("n > 1")
