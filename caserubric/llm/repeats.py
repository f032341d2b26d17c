"""Exact removal of repeated word windows by super-k-mer partitioning.

A window is `width` consecutive words. Its minimiser is the smallest hash among the runs of `seed_words` words within
it; consecutive windows with one minimiser travel as one packed string to the bucket of that minimiser, where sorting
the windows counts them exactly. Equal windows have equal minimisers, so they always meet.

Each task first joins equal strings: a string seen twice there needs no further count for its occurrences, and leaves
once. A passage that a third of the documents share is thus sent once by each task, not once a document.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORD

FIND = re.compile(WORD).findall
BUCKET_BYTES = 48 << 20  # of packed strings in a bucket
#: A string occurred once in its task, once but may hold a window twice, or more often.
ALONE, LOOPS, MANY = 0, 1, 2
COMBINE_BYTES = 32 << 20  # of packed strings that a task joins before it sends them


class WordCodes(dict):
    """64-bit hash of a word, remembered for up to a million words."""

    def __missing__(self, word: str) -> int:
        if len(self) > 1_000_000:
            self.clear()
        code = self[word] = xxhash.xxh64_intdigest(word.encode("utf-8", "surrogatepass"))
        return code


def hashed_runs(codes: np.ndarray, length: int) -> np.ndarray:
    """A 64-bit hash of each run of `length` codes."""
    n = len(codes) - length + 1
    h = np.zeros(max(0, n), np.uint64)
    for j in range(length):
        h = h * np.uint64(0x9E3779B97F4A7C15) + codes[j : j + n]
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def sliding_min(h: np.ndarray, width: int) -> np.ndarray:
    n, step, low = len(h) - width + 1, 1, h
    while step * 2 <= width:
        low = np.minimum(low[:-step], low[step:])
        step *= 2
    return np.minimum(low[:n], low[width - step : width - step + n])


def super_kmers(codes: np.ndarray, width: int, seed_words: int) -> tuple[np.ndarray, np.ndarray, bool]:
    """(first window of each run with one minimiser, with the end appended; the runs' minimisers; whether a run may hold a window twice).

    A window can recur within its run only where the minimiser does.
    """
    h = hashed_runs(codes, seed_words)
    low = sliding_min(h, width - seed_words + 1)
    starts = np.concatenate(([0], np.flatnonzero(low[1:] != low[:-1]) + 1))
    return np.append(starts, len(low)), low[starts], len(np.unique(h)) < len(h)


def spans_blob(rows: list[tuple[int, int, int, int]]) -> bytes:
    return np.array(rows, np.int64).reshape(-1, 4).tobytes()


def packer(width: int, seed_words: int, buckets: int):
    """Arrow batches of (k1, k2, text) to (dest, blob): strings for the bucket dest, or spans (dest + buckets) known already."""

    def flush(seen: dict[str, list], found: list) -> Iterator[pa.RecordBatch]:
        by: dict[int, list] = {}
        for text, x in seen.items():
            by.setdefault(x[0] % buckets, []).append((text, x))
        dest, blobs, press = [], [], zstandard.ZstdCompressor(level=3)
        for d, items in by.items():
            items.sort(key=lambda item: item[1][0])  # strings of one minimiser are alike, so they compress well side by side
            heads = np.array([(x[0], x[1], x[2], x[3], x[4]) for _, x in items], dtype=[("mini", "u8"), ("k1", "i8"), ("k2", "i8"), ("at", "i8"), ("many", "i8")])
            dest.append(d)
            blobs.append(len(items).to_bytes(8, "little") + press.compress(heads.tobytes() + "\n".join(t for t, _ in items).encode("utf-8", "surrogatepass")))
        known: dict[int, list] = {}
        for x in found:
            known.setdefault(x[0] % buckets, []).append(x)
        for d, rows in known.items():
            dest.append(buckets + d)
            blobs.append(spans_blob(rows))
        seen.clear()
        found.clear()
        yield pa.RecordBatch.from_arrays([pa.array(dest, pa.int64()), pa.array(blobs, pa.binary())], ["dest", "blob"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes, seen, found, held = WordCodes(), {}, [], 0
        for batch in batches:
            for k1, k2, text in zip(*(batch.column(c).to_pylist() for c in ("k1", "k2", "text")), strict=True):
                ws = FIND(text or "")
                if len(ws) < width:
                    continue
                runs, minis, loops = super_kmers(np.fromiter(map(codes.__getitem__, ws), np.uint64, len(ws)), width, seed_words)
                runs = runs.tolist()
                for a, b, mini in zip(runs, runs[1:], minis.tolist(), strict=False):
                    packed = " ".join(ws[a : b + width - 1])
                    first = seen.get(packed)
                    if first is None:
                        seen[packed] = [mini, k1, k2, a, ALONE + loops]
                        held += len(packed) + 100
                        continue
                    if first[4] != MANY:
                        first[4] = MANY
                        found.append((first[1], first[2], first[3], first[3] + b - a + width - 1))
                    found.append((k1, k2, a, b + width - 1))
                    held += 40
                if held > COMBINE_BYTES:
                    yield from flush(seen, found)
                    held = 0
        if seen:
            yield from flush(seen, found)

    return run


def repeated_starts(strings: list[tuple[str, bool]], width: int) -> dict[str, list[int]]:
    """For distinct packed strings (and whether each occurs more than once), the starts of the windows that occur twice or more."""
    windows, where = [], []
    for s, (text, _) in enumerate(strings):
        cuts = [-1, *[m.start() for m in re.finditer(" ", text)], len(text)]
        for k in range(len(cuts) - width):
            windows.append(text[cuts[k] + 1 : cuts[k + width]])
            where.append((s, k))
    order = sorted(range(len(windows)), key=windows.__getitem__)
    out: dict[str, list[int]] = {}
    lo = 0
    while lo < len(order):
        hi = lo + 1
        while hi < len(order) and windows[order[hi]] == windows[order[lo]]:
            hi += 1
        if hi - lo > 1 or strings[where[order[lo]][0]][1]:
            for i in order[lo:hi]:
                out.setdefault(strings[where[i][0]][0], []).append(where[i][1])
        lo = hi
    return out


def counter(width: int, seed_words: int, buckets: int):
    """All blobs of a bucket to spans (k1, k2, lo, hi) of words under repeated windows."""
    def run(table: pa.Table) -> pa.Table:
        spans: list[tuple[int, int, int, int]] = []
        blobs = table.column("blob").to_pylist()
        if table.num_rows and table.column("dest")[0].as_py() >= buckets:
            rows = np.concatenate([np.frombuffer(b, np.int64).reshape(-1, 4) for b in blobs])
            return pa.table({k: rows[:, j] for j, k in enumerate(("k1", "k2", "lo", "hi"))})
        heads, texts = [], []
        for blob in blobs:
            n, raw = int.from_bytes(blob[:8], "little"), zstandard.decompress(blob[8:])
            heads.append(np.frombuffer(raw[: 40 * n], dtype=[("mini", "u8"), ("k1", "i8"), ("k2", "i8"), ("at", "i8"), ("many", "i8")]))
            texts += raw[40 * n :].decode("utf-8", "surrogatepass").split("\n")
        head = np.concatenate(heads)
        order = np.argsort(head["mini"], kind="stable")
        mini = head["mini"][order]
        cuts = np.flatnonzero(np.concatenate(([True], mini[1:] != mini[:-1], [True])))
        for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            own = order[lo:hi].tolist()
            if hi - lo == 1 and head["many"][own[0]] != LOOPS:
                continue
            times: dict[str, bool] = {}
            for i in own:
                times[texts[i]] = texts[i] in times or bool(head["many"][i] == MANY)
            at = repeated_starts(list(times.items()), width)
            for i in own:
                if head["many"][i] == MANY:
                    continue
                k1, k2, base = int(head["k1"][i]), int(head["k2"][i]), int(head["at"][i])
                for s in at.get(texts[i], ()):
                    if spans and spans[-1][:2] == (k1, k2) and spans[-1][2] <= base + s <= spans[-1][3]:
                        spans[-1] = (k1, k2, spans[-1][2], max(spans[-1][3], base + s + width))
                    else:
                        spans.append((k1, k2, base + s, base + s + width))
        rows = np.array(spans, np.int64).reshape(-1, 4)
        return pa.table({k: rows[:, j] for j, k in enumerate(("k1", "k2", "lo", "hi"))})

    return run


def keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """docs as (row: the columns but the text, text, k1, k2); the keys are 128 bits of id and text."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    rest = [F.col(f"`{c}`") for c in docs.columns if c != text_col]
    return docs.select(F.struct(*rest).alias("row"), F.col(text_col).alias("text"), F.xxhash64(F.col(id_col), text).alias("k1"), F.xxhash64(text, F.lit(1), F.col(id_col)).alias("k2"))


def repeat_spans(rows: DataFrame, width: int = 35, seed_words: int = 8) -> DataFrame:
    """(k1, k2, lo, hi) from keyed rows: words lo..hi-1 lie under a window that starts elsewhere too."""
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(8, math.ceil(total * (1 + 2 * width / (width - seed_words + 2)) / BUCKET_BYTES))
    packed = rows.select("k1", "k2", "text").mapInArrow(packer(width, seed_words, buckets), "dest long, blob binary")
    return packed.groupBy("dest").applyInArrow(counter(width, seed_words, buckets), "k1 long, k2 long, lo long, hi long")


def cutter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out: list[list] = [[], [], [], []]
        for text, spans in zip(batch.column("text").to_pylist(), batch.column("spans").to_pylist(), strict=True):
            ws = FIND(text or "")
            gone = np.zeros(len(ws) + 1, bool)
            for s in spans or ():
                gone[s["lo"] : s["hi"]] = True
            removed = int(gone.sum())
            kept = " ".join(w for w, g in zip(ws, gone.tolist(), strict=False) if not g) if removed else " ".join(ws)
            for to, x in zip(out, (len(ws), removed, kept if removed else text, hashlib.sha256(kept.encode("utf-8", "surrogatepass")).hexdigest()), strict=True):
                to.append(x)
        arrays = [batch.column("row"), pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.string()), pa.array(out[3], pa.string())]
        yield pa.RecordBatch.from_arrays(arrays, ["row", "n_words", "n_removed", "text", "kept_sha256"])


def remove_repeats(docs: DataFrame, width: int = 35, seed_words: int = 8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: (row: struct of the other columns, n_words, n_removed, text, kept_sha256).

    All words under a window of `width` words that also starts elsewhere are removed, first occurrences included. text
    is unchanged where nothing is removed, else the kept words joined by one space; kept_sha256 is of the joined words
    in either case. Null and empty texts have no words. A row that occurs twice repeats its own windows. Ids may be
    null or repeated; no rows give no rows; other columns pass through whatever their names.
    """
    rows = keyed(docs, id_col, text_col)
    spans = repeat_spans(rows, width, seed_words).groupBy("k1", "k2").agg(F.collect_set(F.struct("lo", "hi")).alias("spans"))
    joined = rows.join(spans, ["k1", "k2"], "left").select("row", "text", "spans")
    kind = rows.schema["row"].dataType.simpleString()
    return joined.mapInArrow(cutter, f"row {kind}, n_words long, n_removed long, text string, kept_sha256 string")
