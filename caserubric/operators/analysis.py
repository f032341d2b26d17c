"""Temporal effect, leakage, agreement, breakdowns, errors, augmentation and comparison."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from ..functions import text as X


def rounded(c: Column) -> Column:
    return F.round(c, 6)


def corr(x: Column, y: Column) -> Column:
    """Pearson's r over the rows that have both; null where a side doesn't vary, for which Spark's own corr raises an error in ANSI mode."""
    both = x.isNotNull() & y.isNotNull()
    a, b = F.when(both, x.cast("double")), F.when(both, y.cast("double"))
    return F.try_divide(F.covar_pop(a, b), F.stddev_pop(a) * F.stddev_pop(b))


# --- temporal -------------------------------------------------------------------------------------------------------


def effective_cutoff(models: DataFrame) -> DataFrame:
    """model_id, eff: the knowledge cutoff, else the release date."""
    return models.select("model_id", F.coalesce("cutoff", "released").alias("eff"))


def post_cutoff(scores: DataFrame, models: DataFrame) -> DataFrame:
    """Scores (with published) of cases newer than the model's effective cutoff."""
    return scores.join(effective_cutoff(models), "model_id").where(F.col("published") > F.col("eff")).drop("eff")


def cutoff_delta(scores: DataFrame, models: DataFrame) -> DataFrame:
    """model_id, full, post, diff, n_post in one pass; the registry is the only other input."""
    s = scores.join(effective_cutoff(models), "model_id")
    late = F.when(F.col("published") > F.col("eff"), F.col("score"))
    out = s.groupBy("model_id").agg(F.avg("score").alias("f"), F.avg(late).alias("p"), F.count(late).alias("n_post"))
    return out.select("model_id", rounded(F.col("f")).alias("full"), rounded(F.col("p")).alias("post"), rounded(F.col("p") - F.col("f")).alias("diff"), "n_post")


def degraded_share(delta: DataFrame) -> DataFrame:
    return delta.agg(F.count("diff").alias("n"), F.sum((F.col("diff") < 0).cast("long")).alias("n_down"), rounded(F.avg((F.col("diff") < 0).cast("double"))).alias("share"), F.min("diff").alias("worst"), F.max("diff").alias("best"))


def degraded_by_family(delta: DataFrame, models: DataFrame, family: str = "access") -> DataFrame:
    """family (null for all), n, n_down, share, mean_diff, worst by rollup."""
    j = delta.join(models.select("model_id", family), "model_id")
    return j.rollup(family).agg(F.count("diff").alias("n"), F.sum((F.col("diff") < 0).cast("long")).alias("n_down"), rounded(F.avg((F.col("diff") < 0).cast("double"))).alias("share"), rounded(F.avg("diff")).alias("mean_diff"), F.min("diff").alias("worst"))


def drop_significance(scores: DataFrame, models: DataFrame) -> DataFrame:
    """model_id, n_pre, n_post, t, df: Welch's test of newer against older cases."""
    s = scores.join(effective_cutoff(models), "model_id").where("score is not null")
    new = F.col("published") > F.col("eff")
    part = lambda c, k: [F.count(F.when(c, F.col("score"))).alias(f"n{k}"), F.avg(F.when(c, F.col("score"))).alias(f"m{k}"), F.var_samp(F.when(c, F.col("score"))).alias(f"v{k}")]
    g = s.groupBy("model_id").agg(*part(~new, 0), *part(new, 1))
    e0, e1 = F.col("v0") / F.col("n0"), F.col("v1") / F.col("n1")
    return g.select("model_id", F.col("n0").alias("n_pre"), F.col("n1").alias("n_post"), F.round((F.col("m1") - F.col("m0")) / F.sqrt(e0 + e1), 4).alias("t"), F.round((e0 + e1) ** 2 / (e0**2 / (F.col("n0") - 1) + e1**2 / (F.col("n1") - 1)), 2).alias("df"))


# The distribution function of the Poisson law of mean 1, at 0 to 6.
POISSON = (0.367879, 0.735759, 0.919699, 0.981012, 0.996340, 0.999406, 0.999917)


def drop_bootstrap(scores: DataFrame, models: DataFrame, b: int = 100, blocks: int = 256, seed: int = 0) -> DataFrame:
    """model_id, low, mid, high, p: the middle and the 95 per cent interval of the drop after the cutoff over b resamples, and the share of them without a drop.

    Cases are dealt to blocks by a hash and added up by block first, so what is resampled is models * blocks * b rows at any
    size. A block's weight in a resample follows a Poisson law and is the same for all models, which pairs them.
    """
    s = scores.where("score is not null").join(effective_cutoff(models), "model_id")
    late = F.when(F.col("published") > F.col("eff"), F.col("score"))
    block = (X.bucket_hash(F.col("case_id").cast("string")) % blocks).cast("long")
    part = s.groupBy("model_id", block.alias("block")).agg(F.count(F.lit(1)).alias("n"), F.sum("score").alias("s"), F.count(late).alias("n1"), F.coalesce(F.sum(late), F.lit(0.0)).alias("s1"))
    cell = scores.sparkSession.range(blocks * b).select((F.col("id") % blocks).alias("block"), F.floor(F.col("id") / blocks).alias("rep"))
    h = X.bucket_hash(F.concat_ws(":", F.lit(str(seed)), F.col("block").cast("string"), F.col("rep").cast("string")))
    times = sum(((h >= int(c * (1 << 24))).cast("int") for c in POISSON), F.lit(0))
    draws = cell.select("block", "rep", times.alias("k")).where("k > 0")  # blocks * b rows at most
    mean = lambda total, n: F.try_divide(F.sum(F.col("k") * F.col(total)), F.sum(F.col("k") * F.col(n)))
    each = part.join(F.broadcast(draws), "block").groupBy("model_id", "rep").agg((mean("s1", "n1") - mean("s", "n")).alias("d"))
    at = lambda q: F.round(F.percentile("d", F.lit(q)), 6)
    return each.groupBy("model_id").agg(at(0.025).alias("low"), at(0.5).alias("mid"), at(0.975).alias("high"), rounded(F.avg((F.col("d") >= 0).cast("double"))).alias("p"))


def score_by_quarter(scores: DataFrame, overlap: int = 2) -> DataFrame:
    """quarter, n, mean, moving (over this and the `overlap - 1` quarters before)."""
    q = scores.where("score is not null").groupBy(F.trunc("published", "quarter").alias("quarter")).agg(F.count(F.lit(1)).alias("n"), F.sum("score").alias("s"))
    w = Window.orderBy("quarter").rowsBetween(1 - overlap, 0)
    return q.select(F.col("quarter").cast("string").alias("quarter"), "n", rounded(F.col("s") / F.col("n")).alias("mean"), rounded(F.sum("s").over(w) / F.sum("n").over(w)).alias("moving"))


def score_by_window(scores: DataFrame, width: int = 1, slide: int | None = None) -> DataFrame:
    """start (first month), n, mean over windows of `width` months, one every `slide` months (tumbling if not given).

    Scores are added up by month first, so a sliding window repeats months, not cases.
    """
    slide = slide or width
    month = F.year("published") * 12 + F.month("published") - 1
    by = scores.where("score is not null").groupBy(month.alias("m")).agg(F.count(F.lit(1)).alias("c"), F.sum("score").alias("s"))
    last = F.floor(F.col("m") / slide) * slide
    starts = F.filter(F.transform(F.sequence(F.lit(0), F.lit(-(-width // slide) - 1)), lambda k: last - k * slide), lambda x: x > F.col("m") - width)
    g = by.select("c", "s", F.explode(starts).alias("w")).groupBy("w").agg(F.sum("c").alias("n"), F.sum("s").alias("s"))
    return g.select(F.make_date((F.col("w") / 12).cast("int"), (F.col("w") % 12 + 1).cast("int"), F.lit(1)).cast("string").alias("start"), "n", rounded(F.col("s") / F.col("n")).alias("mean"))


def trend(scores: DataFrame) -> DataFrame:
    """slope of the score per 30 days."""
    day = F.datediff("published", F.lit("1970-01-01").cast("date"))
    return scores.where("score is not null").agg(F.round(F.regr_slope("score", day / 30.0), 8).alias("slope"))


def aligned_windows(scores: DataFrame, models: DataFrame, days: int = 365) -> DataFrame:
    """Windows of `days` before (negative) and after (from 0) the model's cutoff: n, mean over all models."""
    s = scores.where("score is not null").join(effective_cutoff(models), "model_id")
    w = F.floor((F.datediff("published", "eff") - 1) / days).cast("long")
    return s.groupBy(w.alias("rel_window")).agg(F.count(F.lit(1)).alias("n"), rounded(F.avg("score")).alias("mean"))


def separation_violations(cases: DataFrame, models: DataFrame) -> DataFrame:
    """model_id, n: cases not newer than the model's cutoff, hence open to leakage."""
    eff = F.broadcast(effective_cutoff(models))  # one row a model: a registry, not data
    return cases.join(eff, F.col("published") <= F.col("eff")).groupBy("model_id").agg(F.count(F.lit(1)).alias("n"))


# --- leakage --------------------------------------------------------------------------------------------------------


def ngram_leaks(corpus: DataFrame, items: DataFrame, n: int = 8, item: str = "item_id", doc: str = "doc_id", text: str = "text") -> DataFrame:
    """item, doc, shared, share: item n-grams that a document holds. Only hashes meet; items without n tokens have none."""
    grams = lambda df, k: df.select(k, F.explode(F.array_distinct(F.transform(X.ngrams(X.tokens(text), n), lambda g: F.xxhash64(g)))).alias("g"))
    it = grams(items, item)
    size = it.groupBy(item).agg(F.count(F.lit(1)).alias("size"))
    hit = grams(corpus, doc).join(it, "g").groupBy(item, doc).agg(F.count(F.lit(1)).alias("shared"))
    return hit.join(size, item).select(item, doc, "shared", rounded(F.col("shared") / F.col("size")).alias("share"))


def verbatim_leaks(corpus: DataFrame, items: DataFrame, n: int = 8, item: str = "item_id", doc: str = "doc_id", text: str = "text") -> DataFrame:
    """item, doc where the document contains the whole item: a join on its first n-gram, then a check of the strings."""
    first = items.select(item, F.col(text).alias("needle"), F.xxhash64(F.get(X.ngrams(X.tokens(text), n), F.lit(0))).alias("g"))
    grams = corpus.select(doc, F.explode(F.array_distinct(F.transform(X.ngrams(X.tokens(text), n), lambda g: F.xxhash64(g)))).alias("g"))
    pairs = grams.join(first, "g")
    return pairs.join(corpus.select(doc, F.col(text).alias("hay")), doc).where(F.contains("hay", "needle")).select(item, doc).distinct()


# --- agreement ------------------------------------------------------------------------------------------------------


def approval_rate(ratings: DataFrame, threshold: int = 1) -> DataFrame:
    """dim, rater_id, n, rate: share of ratings at or above the threshold."""
    return ratings.groupBy("dim", "rater_id").agg(F.count("rating").alias("n"), rounded(F.avg((F.col("rating") >= threshold).cast("double"))).alias("rate"))


def agreement(pairs: DataFrame, categories: list[int]) -> DataFrame:
    """n, pa, pe, ac1, kappa of pairs (a, b) over the categories; null pairs are left out."""
    q = len(categories)
    live = pairs.where("a is not null and b is not null")
    share = lambda c, k: F.avg((F.col(c) == k).cast("double"))
    cols = [F.count(F.lit(1)).alias("n"), F.avg((F.col("a") == F.col("b")).cast("double")).alias("pa")]
    cols += [share(c, k).alias(f"{c}{i}") for i, k in enumerate(categories) for c in ("a", "b")]
    g = live.agg(*cols)
    pi = [(F.col(f"a{i}") + F.col(f"b{i}")) / 2 for i in range(q)]
    pe = sum((p * (1 - p) for p in pi), F.lit(0.0)) / (q - 1)
    ke = sum((F.col(f"a{i}") * F.col(f"b{i}") for i in range(q)), F.lit(0.0))
    pa = F.col("pa")
    return g.select("n", rounded(pa).alias("pa"), rounded(pe).alias("pe"), rounded(F.when(pe < 1, (pa - pe) / (1 - pe))).alias("ac1"), rounded(F.when(ke < 1, (pa - ke) / (1 - ke))).alias("kappa"))


def agreement_band(x: Column) -> Column:
    return F.when(x > 0.8, "almost perfect").when(x > 0.6, "substantial").when(x > 0.4, "moderate").when(x > 0.2, "fair").otherwise("slight")


def macro_f1(pairs: DataFrame, pred: str, truth: str) -> DataFrame:
    """f1_yes, f1_no, macro_f1 of 0/1 columns; 0/0 counts as 0."""
    n = lambda p, t: F.sum(((F.col(pred) == p) & (F.col(truth) == t)).cast("long"))
    g = pairs.agg(n(1, 1).alias("tp"), n(1, 0).alias("fp"), n(0, 1).alias("fn"), n(0, 0).alias("tn"))
    wrong = F.col("fp") + F.col("fn")
    f1 = lambda x: F.when(2 * F.col(x) + wrong > 0, 2 * F.col(x) / (2 * F.col(x) + wrong)).otherwise(F.lit(0.0))
    return g.select(rounded(f1("tp")).alias("f1_yes"), rounded(f1("tn")).alias("f1_no"), rounded((f1("tp") + f1("tn")) / 2).alias("macro_f1"))


def beta_tail(a: float, b: float, x: float) -> float:
    """Regularised incomplete beta function by its continued fraction."""
    if x <= 0 or x >= 1:
        return 0.0 if x <= 0 else 1.0
    if x > (a + 1) / (a + b + 2):
        return 1 - beta_tail(b, a, 1 - x)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a
    c, d = 1.0, 1 / max(1e-300, 1 - (a + b) * x / (a + 1))
    h = d
    for m in range(1, 300):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / (1 + num * d or 1e-300)
            c = 1 + num / c or 1e-300
            h *= d * c
        if abs(d * c - 1) < 1e-14:
            break
    return front * h


def pearson_p(r: float | None, n: int) -> float | None:
    """Two-sided p of a correlation; null below three points or where r is undefined."""
    if r is None or n < 3 or r != r:
        return None
    if abs(r) >= 1:
        return 0.0
    t2 = r * r * (n - 2) / (1 - r * r)
    return beta_tail((n - 2) / 2, 0.5, (n - 2) / (n - 2 + t2))


def pearson_test(df: DataFrame, x: str, y: str) -> DataFrame:
    """n, r, p; the sums are distributed, and p is worked out from the one row."""
    one = df.where(F.col(x).isNotNull() & F.col(y).isNotNull()).agg(F.count(F.lit(1)).alias("n"), corr(F.col(x), F.col(y)).alias("r"))
    p = F.udf(pearson_p, DoubleType())
    return one.select("n", rounded(F.col("r")).alias("r"), p("r", F.col("n").cast("int")).alias("p"))


def pearson_pairs(scores: DataFrame, model: str = "model_id") -> DataFrame:
    """a, b, n, r, t of every two models over their common cases; t has n - 2 degrees of freedom and is null where r is 1 or undefined."""
    rows = scores.where("score is not null").groupBy("case_id").agg(F.sort_array(F.collect_list(F.struct(F.col(model).alias("m"), "score"))).alias("s"))
    pair = rows.select(F.explode("s").alias("x"), "s").select("x", F.explode(F.filter("s", lambda y: y["m"] > F.col("x.m"))).alias("y"))
    g = pair.groupBy(F.col("x.m").alias("a"), F.col("y.m").alias("b")).agg(F.count(F.lit(1)).alias("n"), F.round(corr(F.col("x.score"), F.col("y.score")), 5).alias("r"))
    return g.withColumn("t", F.round(F.col("r") * F.sqrt(F.try_divide((F.col("n") - 2).cast("double"), 1 - F.col("r") * F.col("r"))), 3))


def score_histogram(scores: DataFrame, bins: int = 10) -> DataFrame:
    b = F.least(F.floor(F.col("score") * bins), F.lit(bins - 1)).cast("long")
    return scores.where("score is not null").groupBy(b.alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def score_skew(scores: DataFrame, model: str = "model_id") -> DataFrame:
    """model, n, skew of the scores: the third central moment over the variance to the power of 3/2."""
    return scores.where("score is not null").groupBy(model).agg(F.count(F.lit(1)).alias("n"), F.round(F.skewness("score"), 5).alias("skew"))


# --- breakdown ------------------------------------------------------------------------------------------------------


def group_matrix(scores: DataFrame, group: str) -> DataFrame:
    """model_id, group, score, n from scores that carry the group."""
    return scores.where("score is not null").groupBy("model_id", group).agg(rounded(F.avg("score")).alias("score"), F.count(F.lit(1)).alias("n"))


def group_cube(scores: DataFrame, *groups: str) -> DataFrame:
    """The groups (null for all), n, score, lowest and highest, for every combination of them, from one pass over the scores."""
    out = scores.where("score is not null").cube(*groups).agg(F.count(F.lit(1)).alias("n"), rounded(F.avg("score")).alias("score"), rounded(F.min("score")).alias("lowest"), rounded(F.max("score")).alias("highest"))
    return out.select(*groups, "n", "score", "lowest", "highest")


def wide(matrix: DataFrame, group: str, values: list[str]) -> DataFrame:
    return matrix.groupBy("model_id").pivot(group, values).agg(F.first("score"))


def extremes(matrix: DataFrame, group: str, k: int = 3) -> DataFrame:
    """group, mean, side, place: the k weakest and strongest groups over all models."""
    g = matrix.groupBy(group).agg(rounded(F.avg("score")).alias("mean"))
    low = g.withColumn("place", F.row_number().over(Window.orderBy("mean", group))).where(F.col("place") <= k).withColumn("side", F.lit("weak"))
    high = g.withColumn("place", F.row_number().over(Window.orderBy(F.col("mean").desc(), group))).where(F.col("place") <= k).withColumn("side", F.lit("strong"))
    return low.union(high).select(group, "mean", "side", F.col("place").cast("long").alias("place"))


def group_correlation(matrix: DataFrame, group: str) -> DataFrame:
    """g1 < g2, r over models."""
    a = matrix.select("model_id", F.col(group).alias("g1"), F.col("score").alias("s1"))
    b = matrix.select("model_id", F.col(group).alias("g2"), F.col("score").alias("s2"))
    return a.join(b, "model_id").where("g1 < g2").groupBy("g1", "g2").agg(F.round(corr(F.col("s1"), F.col("s2")), 5).alias("r"))


def class_contrast(board: DataFrame, models: DataFrame) -> DataFrame:
    """access, domain, mean over models, n by grouping sets."""
    j = board.join(models, "model_id").select("access", "domain", "score")
    return j.groupingSets([[F.col("access")], [F.col("domain")], [F.col("access"), F.col("domain")]], F.col("access"), F.col("domain")).agg(rounded(F.avg("score")).alias("mean"), F.count(F.lit(1)).alias("n"))


def efficiency(board: DataFrame, models: DataFrame) -> DataFrame:
    """model_id, params_b, score, ratio, on_front: no smaller or equal model scores more."""
    j = board.join(models, "model_id").select("model_id", "params_b", "score")
    best = F.max("score").over(Window.orderBy("params_b").rangeBetween(Window.unboundedPreceding, 0))
    return j.select("model_id", "params_b", "score", rounded(F.col("score") / F.col("params_b")).alias("ratio"), (F.col("score") >= best).alias("on_front"))


# --- errors ---------------------------------------------------------------------------------------------------------


def failed() -> Column:
    met = F.coalesce("met", F.lit(False))
    return F.when(F.col("weight") > 0, ~met).otherwise(met)


def axis_error_rate(judged: DataFrame) -> DataFrame:
    """model_id, axis, rate, positive_only, weighted, n: unmet positive or met negative criteria."""
    bad, w = failed(), F.abs("weight")
    pos = F.col("weight") > 0
    return judged.groupBy("model_id", "axis").agg(rounded(F.avg(bad.cast("double"))).alias("rate"), rounded(F.sum((bad & pos).cast("long")) / F.sum(pos.cast("long"))).alias("positive_only"), rounded(F.sum(F.when(bad, w).otherwise(0)) / F.sum(w)).alias("weighted"), F.count(F.lit(1)).alias("n"))


def worst_per_axis(rates: DataFrame) -> DataFrame:
    return rates.groupBy("axis").agg(F.max_by("model_id", F.struct("rate", -F.col("model_id"))).alias("worst"), F.min_by("model_id", F.struct("rate", "model_id")).alias("best"))


def bottom_k(scores: DataFrame, k: int = 100) -> DataFrame:
    """model_id, case_id, place by raw score, then case; Spark limits each group before the shuffle."""
    place = F.row_number().over(Window.partitionBy("model_id").orderBy("raw", "case_id"))
    return scores.where("raw is not null").withColumn("place", place).where(F.col("place") <= k).select("model_id", "case_id", F.col("place").cast("long").alias("place"))


def root_causes(bottom: DataFrame, judged: DataFrame) -> DataFrame:
    """model_id, case_id, cause: by sign, weight and axis of the costliest failed criterion."""
    rows = judged.where(failed()).join(bottom.select("model_id", "case_id"), ["model_id", "case_id"])
    worst = rows.groupBy("model_id", "case_id").agg(F.max_by(F.struct("weight", "axis"), F.struct(F.abs("weight"), -F.col("criterion_no"))).alias("c"))
    w, a = F.col("c.weight"), F.col("c.axis")
    cause = F.when((w < 0) & (F.abs(w) >= 8), "hallucination").when(w < 0, "guideline overgeneralisation").when(a == 3, "context neglect").when(a == 0, "knowledge gap").when(a == 1, "other_1").when(a == 2, "other_2").otherwise("other_3")
    return worst.select("model_id", "case_id", cause.alias("cause"))


def cause_share(causes: DataFrame) -> DataFrame:
    """cause, n, share, lowest and highest share over the models that have it."""
    per = causes.groupBy("model_id", "cause").agg(F.count(F.lit(1)).alias("c")).withColumn("s", F.col("c") / F.sum("c").over(Window.partitionBy("model_id")))
    g = per.groupBy("cause").agg(F.sum("c").alias("n"), rounded(F.min("s")).alias("lowest"), rounded(F.max("s")).alias("highest"))
    return g.withColumn("share", rounded(F.col("n") / F.sum("n").over(Window.partitionBy())))


def bottom_overlap(bottom: DataFrame, models: DataFrame) -> DataFrame:
    """m1 < m2, shared, jaccard for all pairs of models, those without a common case included."""
    size = bottom.groupBy("model_id").agg(F.count(F.lit(1)).alias("n"))
    a, b = bottom.select(F.col("model_id").alias("m1"), "case_id"), bottom.select(F.col("model_id").alias("m2"), "case_id")
    shared = a.join(b, "case_id").where("m1 < m2").groupBy("m1", "m2").agg(F.count(F.lit(1)).alias("shared"))
    pairs = size.select(F.col("model_id").alias("m1"), F.col("n").alias("n1")).join(F.broadcast(size.select(F.col("model_id").alias("m2"), F.col("n").alias("n2"))), F.col("m1") < F.col("m2"))
    s = F.coalesce("shared", F.lit(0)).cast("long")
    return pairs.join(shared, ["m1", "m2"], "left").select("m1", "m2", s.alias("shared"), rounded(s / (F.col("n1") + F.col("n2") - s)).alias("jaccard"))


# --- augmentation and comparison --------------------------------------------------------------------------------------


def recovery(modes: DataFrame) -> DataFrame:
    """model_id, gain = open - closed, drop = baseline - closed, recovery = gain / drop, null unless the drop is positive."""
    gain, drop = F.col("open") - F.col("closed"), F.col("baseline") - F.col("closed")
    return modes.select("model_id", rounded(gain).alias("gain"), rounded(drop).alias("drop"), rounded(F.when(drop > 0, gain / drop)).alias("recovery"))


def all_improve(modes: DataFrame) -> DataFrame:
    return modes.agg(F.bool_and(F.col("open") > F.col("closed")).alias("all_improve"))


def augment(responses: DataFrame, hits: DataFrame, passages: DataFrame, key: str = "case_id") -> DataFrame:
    """Answers with the retrieved evidence appended, in the order of its rank."""
    ev = hits.join(passages.select("doc_id", F.col("text").alias("ev")), "doc_id").groupBy(key).agg(F.array_sort(F.collect_list(F.struct("rank", "doc_id", "ev"))).alias("e"))
    joined = responses.join(ev, key, "left")
    return joined.withColumn("text", F.concat_ws("\n", "text", F.array_join(F.transform(F.coalesce("e", F.array().cast("array<struct<rank:int,doc_id:bigint,ev:string>>")), lambda x: x["ev"]), "\n"))).drop("e")


def long_tail(cases: DataFrame, by: str) -> DataFrame:
    """by, n, place, share, cumulative share, in descending order of size; the groups are few."""
    g = cases.groupBy(by).agg(F.count(F.lit(1)).alias("n"))
    w = Window.orderBy(F.col("n").desc(), by)
    total = F.sum("n").over(Window.partitionBy())
    return g.select(by, "n", F.row_number().over(w).cast("long").alias("place"), rounded(F.col("n") / total).alias("share"), rounded(F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)) / total).alias("cumulative"))


def gini(tail: DataFrame) -> DataFrame:
    """gini of the sizes n, from their descending places."""
    k, t, z = F.col("k"), F.col("t"), F.col("z")
    return tail.agg(F.count(F.lit(1)).alias("k"), F.sum("n").alias("t"), F.sum(F.col("place") * F.col("n")).alias("z")).select(rounded((k + 1 - 2 * z / t) / k).alias("gini"))


def dataset_profile(cases: DataFrame) -> DataFrame:
    """facet, value, n, share for theme, specialty, source and language by grouping sets, one pass."""
    facets = ["theme", "specialty", "source", "lang"]
    rows = cases.select(F.inline(F.array(*[F.struct(F.lit(f).alias("facet"), F.col(f).cast("string").alias("value")) for f in facets])))
    g = rows.groupBy("facet", "value").agg(F.count(F.lit(1)).alias("n"))
    return g.withColumn("share", rounded(F.col("n") / F.sum("n").over(Window.partitionBy("facet"))))


def criteria_profile(criteria: DataFrame) -> DataFrame:
    """facet, value, n, share: criteria by axis; and the mean, least and most criteria of a case, as value with n cases."""
    axis = criteria.groupBy("axis").agg(F.count(F.lit(1)).alias("n"))
    axis = axis.select(F.lit("axis").alias("facet"), F.col("axis").cast("double").alias("value"), "n", rounded(F.col("n") / F.sum("n").over(Window.partitionBy())).alias("share"))
    per = criteria.groupBy("case_id").agg(F.count(F.lit(1)).alias("c")).agg(F.count(F.lit(1)).alias("n"), F.avg("c").alias("mean"), F.min("c").alias("least"), F.max("c").alias("most"))
    rows = [F.struct(F.lit(f"{k} per case").alias("facet"), rounded(F.col(k).cast("double")).alias("value"), F.col("n").alias("n"), F.lit(None).cast("double").alias("share")) for k in ("mean", "least", "most")]
    return axis.union(per.select(F.inline(F.array(*rows))))


def sample_cases(cases: DataFrame, k: int = 50, seed: int = 42, key: str = "case_id", strata: str | None = None) -> DataFrame:
    """k cases by seeded hash, or k of each stratum; the same rows in any engine."""
    h = F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string")))
    if strata:
        return cases.withColumn("_n", F.row_number().over(Window.partitionBy(strata).orderBy(h, key))).where(F.col("_n") <= k).drop("_n")
    return cases.orderBy(h, key).limit(k)
