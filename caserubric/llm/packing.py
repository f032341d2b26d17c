"""Conflict-constrained best-fit packing of documents into bins of fixed capacity.

A bin takes at most one document of a source and one of a duplicate cluster. Open bins are kept by residual; a
bitmap of the residuals in use gives the successor, the tightest bin that an item fits, and the search goes on to the
next residual until a bin's source and cluster bitmaps have no bit in common with the item's.

Documents are dealt to shards by hash, not by source, and each shard is packed by itself: a hot source or cluster
is spread over all shards, and a shard leaves a few part-filled bins at most.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import publish, words

CAPACITY = 2048  # words
SHARD_DOCS = 4096


def bits_of(values: pd.Series, shared_only: bool) -> list[int]:
    """A bit for each distinct value; 0 for values that occur once, if only shared ones matter."""
    codes, _ = pd.factorize(values, use_na_sentinel=False)
    count = np.bincount(codes, minlength=1)
    places, at = {}, 0
    for c, n in enumerate(count.tolist()):
        places[c] = 0 if shared_only and n < 2 else 1 << at
        at += places[c] > 0
    return [places[c] for c in codes.tolist()]


def best_fit(sizes: list[int], sources: list[int], clusters: list[int], capacity: int) -> list[int]:
    """Bin number of each item, given largest first. Bins of one residual are grouped by source bitmap."""
    levels: list[dict[int, list[int]]] = [{} for _ in range(capacity + 1)]
    used, held, out = 0, [], []  # bitmap of residuals in use; cluster bitmap of each bin
    for size, source, cluster in zip(sizes, sources, clusters, strict=True):
        rest, found, at = used >> size, -1, size
        while rest and found < 0:
            at += (rest & -rest).bit_length() - 1
            for mask, bins in levels[at].items():
                if mask & source:
                    continue
                k = next((k for k, b in enumerate(bins) if not held[b] & cluster), -1)
                if k >= 0:
                    found = bins.pop(k)
                    break
            else:
                at += 1
                rest = used >> at
        if found < 0:
            found, at, mask = len(held), capacity, 0
            held.append(0)
        else:
            if not levels[at][mask]:
                del levels[at][mask]
            if not levels[at]:
                used &= ~(1 << at)
        held[found] |= cluster
        left = at - size
        if left:
            levels[left].setdefault(mask | source, []).append(found)
            used |= 1 << left
        out.append(found)
    return out


def packer(capacity: int):
    def run(shard: pd.DataFrame) -> pd.DataFrame:
        shard = shard.sort_values(["size", "key"], ascending=[False, True], kind="stable").reset_index(drop=True)
        size = shard["size"].to_numpy()
        full, rest = size // capacity, size % capacity
        last = np.flatnonzero(rest > 0)
        last = last[np.argsort(-rest[last], kind="stable")]
        source, cluster = bits_of(shard["source"], False), bits_of(shard["cluster"], True)
        bins = best_fit(rest[last].tolist(), [source[i] for i in last], [cluster[i] for i in last], capacity)
        at = np.concatenate((np.repeat(np.arange(len(shard)), full), last, np.flatnonzero(size == 0)))
        piece = np.concatenate((np.arange(full.sum()) - np.repeat(np.cumsum(full) - full, full), full[last], np.zeros((size == 0).sum(), np.int64))).astype(np.int64)
        of = pd.array([*range(max(bins, default=-1) + 1, max(bins, default=-1) + 1 + int(full.sum())), *[None] * 0], dtype="Int64")
        of = pd.array([*of, *bins, *[None] * int((size == 0).sum())], dtype="Int64")
        count = np.concatenate((np.full(int(full.sum()), capacity), rest[last], np.zeros((size == 0).sum(), np.int64)))
        fill = pd.Series(count).groupby(of).transform("sum") if len(at) else pd.Series([], dtype="int64")
        made = pd.DataFrame({"id": shard["id"].to_numpy(dtype=object)[at] if len(at) else [], "source": shard["source"].to_numpy(dtype=object)[at] if len(at) else [], "cluster": shard["cluster"].to_numpy()[at], "piece": piece, "start_word": piece * capacity, "n_words": count})
        made["bin"] = (of + int(shard["shard"].iloc[0]) * (1 << 24)) if len(at) else pd.array([], dtype="Int64")
        made["bin_words"] = fill.astype("Int64").to_numpy()
        return made

    return run


def pack(docs: DataFrame, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", cluster: Column | None = None) -> DataFrame:
    """One row per piece of a document: id, source, cluster, piece, start_word, n_words, bin, bin_words.

    A text longer than the capacity is cut into pieces of that many words, each a bin of its own, and a last one that
    is packed; every word of every document is in exactly one piece. cluster is the hash of the text unless given, so
    that exact copies never share a bin. A null source is a source of its own. Null and blank texts have one piece of no
    words and a null bin. Repeated rows are packed one by one. No rows give no rows; other columns are ignored.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    group = F.xxhash64(text) if cluster is None else cluster.cast("long")
    kind = docs.select(id_col).schema[0].dataType.simpleString()
    rows = publish(docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), group.alias("cluster"), F.size(words(F.col(text_col))).cast("long").alias("size"), F.xxhash64(F.col(id_col), text).alias("key")), "sizes")
    shards = max(1, math.ceil(rows.count() / SHARD_DOCS))
    # Rows repeated in full are counted, then numbered, so that they are dealt to all shards, and alike in every run.
    each = rows.groupBy(*rows.columns).agg(F.count(F.lit(1)).alias("n")).withColumn("no", F.explode(F.sequence(F.lit(1).cast("long"), F.col("n"))))
    rows = each.select(*rows.columns, F.pmod(F.xxhash64("key", "no"), F.lit(shards)).alias("shard"))
    out = rows.groupBy("shard").applyInPandas(packer(capacity), f"id {kind}, source string, cluster long, piece long, start_word long, n_words long, bin long, bin_words long")
    return out.withColumnRenamed("id", id_col)
