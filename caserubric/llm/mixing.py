"""Mixing sources to target weights by pivotal dependent rounding.

Each document of a source expects the same number of copies, target / source size. The whole part is taken; the
fractional parts are settled by pivots: two open documents of a source trade expected words until one of them is
integral. A trade is a fair lottery, so that every document keeps its expectation, and the words of the source change
only when its last open document is rounded. Blocks of documents, hashed by id and not by source, settle all but
one document of each source; what is left meets in a tree of further blocks.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import publish, words

BLOCK = 20_000  # documents settled by one task at the leaves
FAN_IN = 64  # blocks whose leftovers meet in one task, each with one open document a source


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, ceiling: float = 2.0) -> DataFrame:
    """(source, source_size, target) from (source, size): weights repeat over the sources by code point, null last.

    Targets share `share` times all words by weight, none above `ceiling` times its source's words; what is cut is
    dealt again by weight. Each round is one aggregate over the sources; the sources never meet in a task.
    """
    spark = sizes.sparkSession
    totals = publish(sizes.groupBy("source").agg(F.sum("size").alias("source_size")), "sources")
    ranked = totals.orderBy(F.col("source").asc_nulls_last()).rdd.zipWithIndex().map(lambda x: (x[0][0], x[0][1], x[1]))
    ranked = spark.createDataFrame(ranked, "source string, source_size long, place long")
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.col("place") % len(weights) + 1).cast("int"))
    ranked = publish(ranked.select("source", "source_size", w.alias("weight"), (F.lit(ceiling) * F.col("source_size")).alias("cap")), "weights")
    level = 0.0
    words_all = float(ranked.agg(F.sum("source_size")).first()[0] or 0)
    while True:  # the level rises until no further source is cut, so it ends after as many rounds as there are distinct cuts
        cut = F.col("weight") * F.lit(level) > F.col("cap") if level else F.lit(False)
        fixed, open_w = ranked.agg(F.sum(F.when(cut, F.col("cap")).otherwise(0.0)), F.sum(F.when(cut, 0.0).otherwise(F.col("weight")))).first()
        after = (share * words_all - (fixed or 0.0)) / open_w if open_w else level
        if after <= level * (1 + 1e-12):
            break
        level = after
    return ranked.select("source", "source_size", F.least(F.col("weight") * F.lit(level), F.col("cap")).alias("target"))


def lottery(ids: np.ndarray, seed: int) -> np.ndarray:
    """A number in [0, 1) for each key, the same in every run."""
    x = ids.astype(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15) & 0xFFFFFFFFFFFFFFFF)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return ((x ^ (x >> np.uint64(31))) >> np.uint64(11)) / float(1 << 53)


def pivot(size: np.ndarray, prob: np.ndarray, luck: np.ndarray) -> tuple[np.ndarray, int]:
    """Settle one source's documents within a block; the probabilities after it, and the place of the open one or -1.

    Documents come largest first. Each trades with all that follow it, as one partner whose members give or get in
    proportion, so that a large document is settled by many small ones and the one left open is small.
    """
    p = np.where((prob > 1e-9) & (prob < 1 - 1e-9), prob, np.round(prob))
    free = np.flatnonzero((p > 0) & (p < 1))
    t, q = size[free].astype(float), p[free]
    tail = np.append(np.cumsum(t[::-1])[::-1], 0.0).tolist()
    mass = np.append(np.cumsum((t * q)[::-1])[::-1], 0.0).tolist()
    scale, shift, held = 1.0, 0.0, -1  # those that follow stand at scale * q + shift
    for k, (s, first, lot) in enumerate(zip(t.tolist(), q.tolist(), luck[free].tolist(), strict=True)):
        now = min(1.0, max(0.0, scale * first + shift))
        have = min(tail[k + 1], max(0.0, scale * mass[k + 1] + shift * tail[k + 1]))
        room = tail[k + 1] - have
        up, down = min((1 - now) * s, have), min(now * s, room)  # words that can come to the document, or leave it
        if up + down > 0:
            if lot * (up + down) < down:
                now += up / s
                scale, shift = scale * (1 - up / have), shift * (1 - up / have)
            else:
                now -= down / s
                keep = 1 - down / room
                scale, shift = scale * keep, shift * keep + 1 - keep
        now = now if 1e-9 < now < 1 - 1e-9 else float(round(now))
        p[free[k]] = now
        if 0 < now < 1:
            held = int(free[k])
    return p, held


def settle(frame: pd.DataFrame, seed: int, last: bool) -> pd.DataFrame:
    frame = frame.sort_values(["source", "size", "key"], ascending=[True, False, True], kind="stable", na_position="last").reset_index(drop=True)
    new = frame["prob"].to_numpy(copy=True)
    luck = lottery(frame["key"].to_numpy(), seed)
    size, kind = frame["size"].to_numpy(), frame["source"].fillna("").to_numpy()
    gone = frame["source"].isna().to_numpy()
    starts = [0, *(np.flatnonzero((kind[1:] != kind[:-1]) | (gone[1:] != gone[:-1])) + 1), len(frame)] if len(frame) else [0]
    for lo, hi in zip(starts, starts[1:], strict=False):
        new[lo:hi], held = pivot(size[lo:hi], new[lo:hi], luck[lo:hi])
        if last and held >= 0:
            new[lo + held] = float(luck[lo + held] < new[lo + held])
    return frame.assign(prob=new)


def settler(seed: int, last: bool):
    return lambda frame: settle(frame, seed, last)


def mix(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, ceiling: float = 2.0, seed: int = 17, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """One row per document: id, source, size, source_size, target (of its source), copies,
    taken = copies * size, key (hash of id and text).

    size counts the words of the whole text, 0 for null. A null source is a source of its own. Copies are 0 .. ceil of
    the ceiling, and reruns agree: all lots hang on (id, text). Rows repeated in full are drawn one by one and are
    interchangeable. Sources without words take nothing. No rows give no rows; other columns are ignored.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    base = publish(docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), F.size(words(text)).cast("long").alias("size"), F.xxhash64(F.col(id_col), text).alias("key")), "sizes")
    goal = publish(source_targets(base, weights, share, ceiling), "targets")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    n = base.count()
    blocks = max(1, math.ceil(n / BLOCK))
    rows = base.join(goal.withColumn("rate", rate).withColumnRenamed("source", "of"), F.col("source").eqNullSafe(F.col("of"))).drop("of")
    rows = rows.withColumn("whole", F.when(F.col("size") > 0, F.floor("rate")).otherwise(0).cast("long"))
    rows = rows.withColumn("prob", F.when(F.col("size") > 0, F.col("rate") - F.col("whole")).otherwise(0.0)).drop("rate")
    rows = rows.withColumn("block", F.pmod(F.xxhash64("key"), F.lit(blocks)))
    done, level = [], 0
    while True:
        last = blocks == 1
        settled = publish(rows.groupBy("block").applyInPandas(settler(seed + level, last), rows.schema), f"level{level}")
        is_open = (F.col("prob") > 0) & (F.col("prob") < 1)
        done.append(settled.where(~is_open))
        if last:
            break
        blocks, level = math.ceil(blocks / FAN_IN), level + 1
        rows = settled.where(is_open).withColumn("block", F.floor(F.col("block") / FAN_IN).cast("long"))
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    copies = F.col("whole") + F.col("prob").cast("long")
    return out.select(F.col("id").alias(id_col), "source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"), "key")


def repeated(docs: DataFrame, mixed: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with each document as often as mixed takes it; the columns of docs, whatever their names. Rows of one id and text are drawn together."""
    key = F.xxhash64(F.col(id_col), F.coalesce(F.col(text_col), F.lit("")))
    times = mixed.groupBy("key").agg(F.sum("copies").cast("int").alias("copies")).where("copies > 0")
    rows = docs.select(key.alias("key"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    joined = rows.join(times, "key").dropDuplicates(["key"])
    return joined.select("row", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("row.*")
