"""Platform choice, the eight post filters with their funnel, and duplicates."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as X


def weekly_activity(posts: DataFrame, platform: str, ts: str, weeks: int) -> DataFrame:
    """platform, active_weeks, ok: whether the platform has a post in at least `weeks` weeks and in every week between its first and last."""
    return posts.groupBy(platform).agg(F.countDistinct(week_of(ts)).alias("active_weeks"), span_weeks(ts).alias("_span")).select(platform, "active_weeks", every_week(weeks).alias("ok"))


def week_of(ts: str) -> Column:
    return F.date_trunc("week", F.col(ts)).cast("date")


def span_weeks(ts: str) -> Column:
    """Weeks from the first to the last, both included."""
    return (F.datediff(F.max(week_of(ts)), F.min(week_of(ts))) / 7).cast("long") + 1


def every_week(weeks: int) -> Column:
    return (F.col("active_weeks") >= weeks) & (F.col("active_weeks") == F.col("_span"))


def verified_count(posts: DataFrame, platform: str, author: str, min_n: int, approx: bool = False, rsd: float = 0.02) -> DataFrame:
    n = F.approx_count_distinct(author, rsd) if approx else F.countDistinct(author)
    return posts.groupBy(platform).agg(n.alias("n_verified")).withColumn("ok", F.col("n_verified") >= min_n)


def endorsed(platforms: DataFrame, registry: DataFrame, platform: str) -> DataFrame:
    """Platforms that the registry names; Spark broadcasts the registry if it is small."""
    return platforms.join(registry.select(platform), platform, "left_semi")


def select_platforms(posts: DataFrame, registry: DataFrame, platform: str, ts: str, author: str, weeks: int, min_n: int) -> DataFrame:
    """platform, active, endorsed, verified, selected in one pass over the posts."""
    seen = posts.groupBy(platform).agg(F.countDistinct(week_of(ts)).alias("active_weeks"), F.countDistinct(author).alias("n_verified"), span_weeks(ts).alias("_span"))
    flags = seen.join(registry.select(platform, F.lit(True).alias("named")), platform, "left")
    out = flags.select(platform, every_week(weeks).alias("active"), F.coalesce("named", F.lit(False)).alias("endorsed"), (F.col("n_verified") >= min_n).alias("verified"))
    return out.withColumn("selected", F.col("active") & F.col("endorsed") & F.col("verified"))


def published_since(ts: Column, floor: str) -> Column:
    return ts >= F.lit(floor).cast("date")


def tag_allowed(tags: Column, allow: list[str], deny: list[str]) -> Column:
    """A relevant tag and no off-topic one; null tags are not allowed."""
    one_of = lambda names: F.coalesce(F.arrays_overlap(tags, F.array(*map(F.lit, names))), F.lit(False))
    return one_of(allow) & ~one_of(deny)


SCHEMES = ("disease", "function", "intervention")
LONGEST_TERM = 3  # words of a code term


def codebook(items: DataFrame, text: str = "text", least: int = 9) -> DataFrame:
    """(term, scheme): the long tokens of the items and the runs of two tokens of which the first is long, dealt to three schemes."""
    toks = X.tokens(text)
    long = lambda t: F.length(t) >= least
    pairs = F.filter(X.ngrams(toks, 2), lambda g: long(F.substring_index(g, " ", 1)))
    terms = items.select(F.explode(F.array_distinct(F.concat(F.filter(toks, long), pairs))).alias("term")).distinct()
    return terms.select("term", F.element_at(F.array(*map(F.lit, SCHEMES)), X.bucket_hash("term") % len(SCHEMES) + 1).alias("scheme"))


def code_hits(df: DataFrame, key: str, text: str, book: DataFrame, schemes: tuple[str, ...] | None = None) -> DataFrame:
    """key, matched: sorted code terms of each row that has one, of the given schemes or of any.

    Runs of tokens meet the book by an equi-join, never by a large pattern; runs whose first word begins no term are
    dropped by a semi join before the others are made.
    """
    book = book if schemes is None else book.where(F.col("scheme").isin(*schemes))
    runs = F.array_distinct(F.concat(*[X.ngrams(X.tokens(text), n) for n in range(1, LONGEST_TERM + 1)]))
    words = df.select(key, F.explode(F.filter(runs, lambda g: F.length(F.substring_index(g, " ", 1)) >= 9)).alias("term"))
    return words.join(book.select("term").distinct(), "term").groupBy(key).agg(F.sort_array(F.collect_set("term")).alias("matched"))


def has_verified_reply(messages: DataFrame) -> DataFrame:
    return messages.groupBy("thread_id").agg(F.bool_or(F.col("role") == "assistant").alias("ok"))


@dataclass(frozen=True)
class Rule:
    name: str
    test: Column


def post_filter(posts: DataFrame, rules: list[Rule]) -> DataFrame:
    """posts with reasons, the names of the rules that fail in order, and kept. A null test fails."""
    failing = [F.when(~F.coalesce(r.test, F.lit(False)), F.lit(r.name)) for r in rules]
    return posts.withColumn("reasons", F.array_compact(F.array(*failing))).withColumn("kept", F.size("reasons") == 0)


def filter_funnel(posts: DataFrame, rules: list[Rule], ablate: bool = False) -> DataFrame:
    """step, rule, remaining, removed (and without, what is left when this rule is switched off) in one pass."""
    tests = [F.coalesce(r.test, F.lit(False)) for r in rules]
    sums, passed = [F.count(F.lit(1)).alias("n0")], F.lit(True)
    for k, t in enumerate(tests):
        passed = passed & t
        sums.append(F.coalesce(F.sum(passed.cast("long")), F.lit(0)).alias(f"n{k + 1}"))
        if ablate:
            others = F.lit(True)
            for j, o in enumerate(tests):
                others = others & o if j != k else others
            sums.append(F.coalesce(F.sum(others.cast("long")), F.lit(0)).alias(f"w{k + 1}"))
    rows = [F.struct(F.lit(0).alias("step"), F.lit("all").alias("rule"), F.col("n0").alias("remaining"), F.lit(0).cast("long").alias("removed"), *([F.col("n0").alias("without")] if ablate else []))]
    for k, r in enumerate(rules):
        rows.append(F.struct(F.lit(k + 1).alias("step"), F.lit(r.name).alias("rule"), F.col(f"n{k + 1}").alias("remaining"), (F.col(f"n{k}") - F.col(f"n{k + 1}")).alias("removed"), *([F.col(f"w{k + 1}").alias("without")] if ablate else [])))
    return posts.agg(*sums).select(F.inline(F.array(*rows)))


def exact_groups(df: DataFrame, key: str, text: str) -> DataFrame:
    """key, dup_of: the smallest key with the same normalised text, null for the first of its group."""
    norm = F.md5(F.lower(F.trim(F.regexp_replace(F.coalesce(F.col(text), F.lit("")), r"[ \t\r\n]+", " "))))
    named = df.select(key, norm.alias("h"))
    first = named.groupBy("h").agg(F.min(key).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1")
    return named.join(first, "h", "left").select(key, F.when(F.col(key) > F.col("first"), F.col("first")).alias("dup_of"))


def drop_indexed(posts: DataFrame, index: DataFrame, key: str, text: str) -> DataFrame:
    """Posts whose text the index lacks, the first of each text only."""
    norm = lambda: F.xxhash64(F.lower(F.trim(F.regexp_replace(F.coalesce(F.col(text), F.lit("")), r"[ \t\r\n]+", " "))))
    fresh = posts.withColumn("_h", norm()).join(index.select(norm().alias("_h")).distinct(), "_h", "left_anti")
    return fresh.withColumn("_n", F.row_number().over(Window.partitionBy("_h").orderBy(key))).where("_n = 1").drop("_h", "_n")


def near_pairs(df: DataFrame, key: str, text: str, threshold: float = 0.8, width: int = 5, bands: int = 16, rows: int = 4) -> DataFrame:
    """(a, b, jaccard) of texts at or above the threshold, candidates by min-hash bands, verified on the shingle sets.

    Equal texts are joined first, so a group of copies is one row under its smallest key; copy_pairs gives the others. All
    pairs of a band are compared, so the work grows with the square of the texts that share one.
    """
    toks = X.tokens(text)
    grams = F.array_distinct(F.when(F.size(toks) >= width, X.ngrams(toks, width)).otherwise(F.array(F.array_join(toks, " "))))
    one = df.groupBy(text).agg(F.min(key).alias("k")).select("k", F.transform(grams, lambda g: F.xxhash64(g)).alias("s"))
    least = lambda i: F.array_min(F.transform("s", lambda h: F.xxhash64(h, F.lit(i))))
    mins = F.array(*map(least, range(bands * rows)))
    signed = one.select("k", "s", mins.alias("m"))
    keyed = signed.select("k", F.posexplode(F.array(*[F.xxhash64(F.slice("m", 1 + b * rows, rows)) for b in range(bands)])).alias("band", "v"))
    pairs = keyed.alias("x").join(keyed.alias("y"), (F.col("x.band") == F.col("y.band")) & (F.col("x.v") == F.col("y.v")) & (F.col("x.k") < F.col("y.k"))).select(F.col("x.k").alias("a"), F.col("y.k").alias("b")).distinct()
    sets = one.select("k", "s")
    both = pairs.join(sets.select(F.col("k").alias("a"), F.col("s").alias("sa")), "a").join(sets.select(F.col("k").alias("b"), F.col("s").alias("sb")), "b")
    inter = F.size(F.array_intersect("sa", "sb"))
    return both.select("a", "b", (inter / (F.size("sa") + F.size("sb") - inter)).alias("jaccard")).where(F.col("jaccard") >= threshold)


def copy_pairs(df: DataFrame, key: str, text: str) -> DataFrame:
    """(a, b, jaccard 1): each further key of a text beside the smallest key of that text, which stands for it in near_pairs."""
    first = df.groupBy(F.col(text).alias("_t")).agg(F.min(key).alias("a"), F.count(F.lit(1)).alias("n")).where("n > 1")
    named = df.select(F.col(key).alias("b"), F.col(text).alias("_u")).join(first, F.col("_u").eqNullSafe(F.col("_t")))
    return named.where("b > a").select("a", "b", F.lit(1.0).alias("jaccard")).distinct()


def harvest_week(posts: DataFrame, week_start: str, ts: str = "posted_at") -> DataFrame:
    lo = F.lit(week_start).cast("timestamp")
    return posts.where((F.col(ts) >= lo) & (F.col(ts) < lo + F.expr("INTERVAL 7 DAYS"))).withColumn("harvest_week", F.lit(week_start).cast("date"))
