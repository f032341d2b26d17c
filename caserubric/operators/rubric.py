"""Rubrics: theme, bipolar criteria, axis and weight, with checks; and responders to grade against them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import text as X

AXES = ("accuracy", "completeness", "communication", "context", "safety")


def dominant_theme(advice: Column, themes: int = 5) -> Column:
    """The theme, by number, with most content tokens of the advice; ties go to the smaller number."""
    toks = X.content(F.array_join(advice, " "))
    of = lambda i: F.size(F.filter(toks, lambda t: F.length(t) % themes == i))
    votes = [of(i) for i in range(themes)]
    most, out = F.greatest(*votes), F.lit(None).cast("int")
    for i in reversed(range(themes)):
        out = F.when(votes[i] == most, i).otherwise(out)
    return out


def facts_for_theme(advice: Column, theme: Column, themes: int = 5, cap: int | None = None) -> Column:
    """Advice with a token of the theme, up to cap sentences if that is given; all of it where none has."""
    own = F.filter(advice, lambda s: F.exists(X.content(s), lambda t: F.length(t) % themes == theme))
    facts = F.when(F.size(own) > 0, own).otherwise(advice)
    return facts if cap is None else F.slice(facts, 1, cap)


def assign_axis(text: Column) -> Column:
    return (X.bucket_hash(text) % len(AXES)).cast("int")


def assign_weight(text: Column, polarity: Column) -> Column:
    """Magnitude 1 to 10 with the sign of the polarity; 10 marks what is critical."""
    return (polarity * (F.lit(1) + F.floor(X.bucket_hash(text) / len(AXES)).cast("int") % 10)).cast("int")


def build_rubric(screened: DataFrame, per_case: int = 2) -> DataFrame:
    """case_id, criterion_no, criterion, polarity, axis, weight, in long form.

    Positive criteria are the advice that fits the dominant theme. Negative ones are facts of the next thread that the case's
    own advice doesn't cover, at most per_case.
    """
    cases = screened.where("forwarded").select(F.col("thread_id").alias("case_id"), "advice", "facts")
    foreign = cases.select((F.col("case_id") - 1).alias("case_id"), F.col("facts").alias("foreign"))
    both = X.fixed(cases.join(foreign, "case_id", "left"), own=X.content(F.array_join("advice", " ")), theme=dominant_theme(F.col("advice")))
    good = facts_for_theme(F.col("advice"), F.col("theme"))
    bad = F.slice(F.filter(F.coalesce("foreign", F.array().cast("array<string>")), lambda s: X.coverage_of(X.content(s), F.col("own")) < 0.5), 1, per_case)
    tagged = lambda xs, p: F.transform(xs, lambda s: F.struct(s.alias("criterion"), F.lit(p).alias("polarity")))
    rows = both.select("case_id", F.posexplode(F.concat(tagged(good, 1), tagged(bad, -1))).alias("n", "c"))
    c, p = F.col("c.criterion"), F.col("c.polarity")
    return rows.select("case_id", (F.col("n") + 1).cast("int").alias("criterion_no"), c.alias("criterion"), p.alias("polarity"), assign_axis(c).alias("axis"), assign_weight(c, p).alias("weight"))


def check_rubric(rubric: DataFrame) -> DataFrame:
    """case_id, criterion_no, violation: one row for each broken rule; criterion_no is null for rules on a whole case."""
    w = F.col("weight")
    own = F.array_compact(F.array(F.when((F.abs(w) > 10) | w.isNull(), F.lit("range")), F.when(w == 0, F.lit("zero")), F.when(F.signum(w.cast("double")) != F.col("polarity"), F.lit("sign"))))
    each = rubric.select("case_id", "criterion_no", F.explode(own).alias("violation"))
    none = F.lit(None).cast("int")
    lacking = rubric.groupBy("case_id").agg(F.max("weight").alias("w")).where("w <= 0 or w is null").select("case_id", none.alias("criterion_no"), F.lit("no positive").alias("violation"))
    if "criterion" not in rubric.columns:
        return each.union(lacking)
    twice = rubric.groupBy("case_id", "criterion").agg(F.count(F.lit(1)).alias("n"), F.max("criterion_no").alias("criterion_no")).where("n > 1").select("case_id", "criterion_no", F.lit("duplicate").alias("violation"))
    return each.union(lacking).union(twice)


def unique_criteria(rubric: DataFrame) -> DataFrame:
    norm = F.md5(F.lower(F.trim("criterion")))
    return rubric.groupBy(norm.alias("criterion_hash")).agg(F.count(F.lit(1)).alias("uses"), F.min("case_id").alias("first_case"))


RESPONDERS = ("reference", "half", "echo", "foreign", "tainted")


def synthetic_responses(screened: DataFrame) -> DataFrame:
    """model, case_id, text of five responders: the whole advice, its first half, the patient's words, the next thread's advice, and the advice with a foreign fact."""
    cases = screened.where("forwarded").select(F.col("thread_id").alias("case_id"), "advice", "facts")
    other = cases.select((F.col("case_id") - 1).alias("case_id"), F.col("advice").alias("oa"), F.col("facts").alias("of"))
    both = cases.join(other, "case_id", "left")
    empty = F.array().cast("array<string>")
    texts = [F.col("advice"), F.slice("advice", 1, F.ceil(F.size("advice") / 2).cast("int")), F.col("facts"), F.coalesce("oa", empty), F.concat("advice", F.slice(F.coalesce("of", empty), 1, 1))]
    rows = [F.struct(F.lit(n).alias("model"), F.array_join(t, ". ").alias("text")) for n, t in zip(RESPONDERS, texts, strict=True)]
    return both.select("case_id", F.inline(F.array(*rows)))


def perturb(text: Column, seed: int = 7) -> Column:
    """Drop about one token in eight and keep the rest in order: a rewritten but not a newer case."""
    toks = F.split(text, " ")
    return F.array_join(F.filter(toks, lambda t: X.bucket_hash(F.concat(F.lit(f"{seed}:"), t)) % 8 != 0), " ")
