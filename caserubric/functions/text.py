"""Expressions on text; all stay inside Spark's own functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Function words that tell the four languages of the tables apart.
LANGUAGE_WORDS = {
    "de": ("der", "die", "das", "und", "ist", "nicht", "ein", "eine", "mit", "von", "auf", "für", "sich", "zu"),
    "en": ("the", "of", "and", "to", "is", "that", "for", "with", "by", "this", "be", "was", "it"),
    "es": ("el", "los", "las", "del", "y", "por", "con", "para", "una", "su", "como", "se"),
    "fr": ("le", "les", "et", "une", "du", "qui", "pour", "dans", "par", "est", "elle", "au"),
}
MEDIA = r"(?i)<(img|video|audio|iframe|embed|object)\b|\.(png|jpe?g|gif|mp4|mp3|wav)\b|\[(image|photo|video|audio)\]"


def col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def tokens(c: Column | str) -> Column:
    return F.regexp_extract_all(F.lower(col(c)), F.lit(r"([\p{L}\p{N}]+)"), F.lit(1))


def sentences(c: Column | str) -> Column:
    cut = F.transform(F.split(col(c), r"[.!?\n]+", -1), lambda s: F.trim(s))
    return F.filter(cut, lambda s: F.length(s) >= 3)


def content(c: Column | str) -> Column:
    """Distinct tokens of four letters and more."""
    return F.array_distinct(F.filter(tokens(c), lambda t: F.length(t) >= 4))


def coverage_of(a: Column, b: Column) -> Column:
    """Share of the content array a that b holds; 0 for an empty a."""
    return F.when(F.size(a) > 0, F.size(F.array_intersect(a, b)) / F.size(a)).otherwise(F.lit(0.0))


def coverage(a: Column | str, b: Column | str) -> Column:
    return coverage_of(content(a), content(b))


def bucket_hash(c: Column | str) -> Column:
    return F.conv(F.substring(F.md5(col(c)), 1, 6), 16, 10).cast("int")


def symbol_share(c: Column | str, count_space: bool = True) -> Column:
    """Share of characters that are no letters or digits; an empty or null text counts as 1."""
    text = F.coalesce(col(c), F.lit(""))
    text = text if count_space else F.regexp_replace(text, r"\s", "")
    return F.when(F.length(text) > 0, F.length(F.regexp_replace(text, r"[\p{L}\p{N}]", "")) / F.length(text)).otherwise(F.lit(1.0))


def text_only(c: Column | str) -> Column:
    return ~F.coalesce(col(c), F.lit("")).rlike(MEDIA)


def language(c: Column | str) -> Column:
    """Chinese if Han characters make up a fifth of the text; else the most function words, ties by name; null if none."""
    t, n = tokens(c), F.greatest(F.length(col(c)), F.lit(1))
    han = F.length(col(c)) - F.length(F.regexp_replace(col(c), r"[\x{4E00}-\x{9FFF}]", ""))
    among = lambda words: F.size(F.filter(t, lambda x: x.isin(*words)))
    votes = {k: among(w) for k, w in sorted(LANGUAGE_WORDS.items())}
    most = F.greatest(*votes.values())
    out = F.when(han / n >= 0.2, F.lit("zh"))
    for k, v in votes.items():
        out = out.when((v == most) & (most > 0), F.lit(k))
    return out


def fixed(df: DataFrame, **cols: Column) -> DataFrame:
    """df with columns that are worked out once a row, even where a lambda refers to them: the optimiser doesn't inline past a generator."""
    return df.select("*", F.inline(F.array(F.struct(*[c.alias(k) for k, c in cols.items()]))))


def ngrams(toks: Column, n: int) -> Column:
    """Runs of n tokens, joined by blanks; the tokens stay outside the lambda, so they are worked out once."""
    shifted = F.arrays_zip(*[F.slice(toks, j + 1, F.greatest(F.size(toks) - j, F.lit(0))).alias(f"t{j}") for j in range(n)])
    return F.transform(F.slice(shifted, F.lit(1), F.greatest(F.size(toks) - (n - 1), F.lit(0))), lambda z: F.concat_ws(" ", *[z[f"t{j}"] for j in range(n)]))


def page_text(html: Column | str) -> Column:
    """struct<title, body, lang, media> of a raw page."""
    h = F.coalesce(col(html), F.lit(""))
    bare = F.regexp_replace(h, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    plain = F.regexp_replace(F.regexp_replace(bare, r"(?s)<[^>]*>", " "), r"\s+", " ")
    for name, sign in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        plain = F.replace(plain, F.lit(name), F.lit(sign))
    return F.struct(F.trim(F.regexp_extract(h, r"(?is)<title[^>]*>(.*?)</title>", 1)).alias("title"), F.trim(plain).alias("body"), F.regexp_extract(h, r'(?i)<html[^>]*\blang="?([A-Za-z-]+)', 1).alias("lang"), F.regexp_extract_all(h, F.lit(r"(?i)<(img|video|audio)\b"), F.lit(1)).alias("media"))
