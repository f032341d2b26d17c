"""Quality classifier from weak labels.

Heuristic labellers vote good, bad or nothing on each document. Expectation-maximisation over the counts of vote
patterns, which are few whatever the corpus, estimates how each labeller votes on good and on bad documents. The
posteriors label a bounded sample, on which a linear scorer over hashed tokens and token shapes is trained; the scorer
rates every whole text. Toxic documents are told by listed words and by a second linear scorer over hashed words and
beginnings of words, fitted on a bounded sample of labelled rows; they are rejected apart from their quality.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORD, publish
from .neardup import mixed

FIND = re.compile(WORD).findall
BINS = 1 << 14
SAMPLE_DOCS = 4000  # expected size of the training sample, whatever the corpus
LABELLED_DOCS = 20_000  # expected number of labelled rows on which the toxic scorer is fitted
CHUNK_TOKENS = 20_000  # tokens that are looked up at a time
HARM_BINS = 1 << 17  # hashed words and beginnings of words of the toxic scorer

# Frequent function words of English, German, French and Spanish.
STOP_WORDS = frozenset(
    "the of and to in is that for it with as on by this be are or an from at was "
    "der die das und ist nicht ein eine zu mit den von auf für im sich des "
    "le la les et un une en du que qui pour dans par est elle au "
    "el los las del de y por con para se su como".split()
)
# Abusive words.
ABUSE = ("clown", "disgusting", "idiot", "loser", "moron", "pathetic", "scum", "stupid", "trash", "worthless")
PARTS = re.compile(r"\w+").findall

#: Labellers: signal, and the ranges of it that vote good and bad; between them the labeller abstains.
LABELLERS = (
    ("symbols", (0.0, 0.05), (0.08, 1.0)),
    ("capitals", (0.0, 0.08), (0.2, 1.0)),
    ("variety", (0.5, 1.0), (0.0, 0.3)),
    ("function_words", (0.13, 1.0), (0.0, 0.08)),
    ("stutter", (0.0, 0.05), (0.2, 1.0)),
    ("bare_marks", (0.0, 0.04), (0.1, 1.0)),
)
SIGNALS = tuple(x[0] for x in LABELLERS)


ALNUM, ALPHA, UPPER, DIGIT = 1, 2, 4, 8


class Kinds:
    """What characters are, looked up once each."""

    def __init__(self):
        self.known = np.full(0x110000, 255, np.uint8)

    def of(self, chars: np.ndarray) -> np.ndarray:
        kind = self.known[chars]
        new = np.unique(chars[kind == 255])
        if len(new):
            self.known[new] = [ALNUM * c.isalnum() + ALPHA * c.isalpha() + UPPER * c.isupper() + DIGIT * c.isdigit() for c in map(chr, new.tolist())]
            kind = self.known[chars]
        return kind


def spelled(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The characters of words that aren't empty, one after another, the words' lengths, and where they start."""
    chars = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)
    size = np.fromiter(map(len, words), np.int64, len(words))
    return chars, size, np.cumsum(size) - size


def run_hashes(chars: np.ndarray, size: np.ndarray, start: np.ndarray) -> np.ndarray:
    """For each character a hash of its word up to it."""
    place = np.arange(len(chars)) - np.repeat(start, size)
    one = mixed(chars.astype(np.uint64) | (place.astype(np.uint64) << np.uint64(32)), 0x5E11)
    total = np.cumsum(one)
    return total - np.repeat(total[start] - one[start], size)


def bins_of(hashes: np.ndarray, salt: int, bins: int) -> np.ndarray:
    return (mixed(hashes, salt) % np.uint64(bins)).astype(np.int32)


def shape_bins(chars: np.ndarray, size: np.ndarray, start: np.ndarray, kind: np.ndarray) -> np.ndarray:
    """The bins of the words with A for capitals, a for other letters and 0 for digits; a run of one character counts once."""
    shape = np.where(kind & UPPER, 65, np.where(kind & ALPHA, 97, np.where(kind & DIGIT, 48, chars))).astype(np.uint32)
    fresh = np.concatenate(([True], shape[1:] != shape[:-1]))
    fresh[start] = True
    kept = np.add.reduceat(fresh, start, dtype=np.int64)
    first = np.cumsum(kept) - kept
    return bins_of(run_hashes(shape[fresh], kept, first)[first + kept - 1], 0x5A, BINS)


def harm_bins(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """The bins of lower-case words, each itself and its beginnings of 2 to 8 characters, and for each bin the word's number."""
    if not words:
        return np.empty(0, np.int32), np.empty(0, np.int64)
    chars, size, start = spelled(words)
    upto = run_hashes(chars, size, start)
    place = np.arange(len(chars)) - np.repeat(start, size)
    begins = np.flatnonzero((place >= 1) & (place < 8))
    owner = np.repeat(np.arange(len(words)), size)[begins]
    bins = np.concatenate((bins_of(upto[start + size - 1], 0x77, HARM_BINS), bins_of(upto[begins], 0x70, HARM_BINS)))
    return bins, np.concatenate((np.arange(len(words)), owner))


def harm_scale(n):
    """A feature counts by its share of the n words, in units of 50; 20 words are added so that short texts aren't all or nothing."""
    return 50.0 / (n + 20)


class Tokens(dict):
    """Tokens numbered as they come, with a row of facts for each; forgotten between texts beyond half a million.

    Facts: symbols, capitals, letters, stop word, bare mark, length, toxic, and the bins of the token and of its shape.
    worth is the sum of the weights of both bins; harm the toxic weights of the token's words and their number, if asked.
    """

    def __init__(self, toxic: frozenset[str] = frozenset(), weights: np.ndarray | None = None, harmful: np.ndarray | None = None):
        super().__init__()
        self.toxic, self.weights, self.harmful = toxic, weights, harmful
        self.kinds = Kinds()
        self.facts, self.worth, self.harm = np.zeros((4096, 9), np.int32), np.zeros(4096), np.zeros((4096, 2))
        self.fresh: list[str] = []  # tokens that the arrays don't have yet

    def __missing__(self, w: str) -> int:
        self.fresh.append(w)
        k = self[w] = len(self)
        return k

    def numbers(self, ws: list[str]) -> np.ndarray:
        if len(self) > 500_000:
            self.clear()
        old = len(self)
        at = np.fromiter(map(self.__getitem__, ws), np.int64, len(ws))
        if self.fresh:
            if len(self) > len(self.worth):
                more = max(len(self), 2 * len(self.worth)) - len(self.worth)
                self.facts, self.worth = np.concatenate((self.facts, np.zeros((more, 9), np.int32))), np.concatenate((self.worth, np.zeros(more)))
                self.harm = np.concatenate((self.harm, np.zeros((more, 2))))
            self.learn(self.fresh, slice(old, len(self)))
            self.fresh = []
        return at

    def learn(self, words: list[str], at: slice) -> None:
        """Fill the rows of new tokens, all at once."""
        low = [w.lower() for w in words]
        chars, size, start = spelled(words)
        kind = self.kinds.of(chars)
        alnum, letters, capitals = (np.add.reduceat(kind & x > 0, start, dtype=np.int32) for x in (ALNUM, ALPHA, UPPER))
        marks = size - alnum
        plain = [x.isalnum() for x in low]
        parts = [(x,) if whole else PARTS(x) for x, whole in zip(low, plain, strict=True)]
        toxic = [not self.toxic.isdisjoint(p) for p in parts] if self.toxic else np.zeros(len(words), bool)
        stop = [x.strip(".,;:!?") in STOP_WORDS for x in low]
        spelling = spelled(low)
        name = bins_of(run_hashes(*spelling)[spelling[2] + spelling[1] - 1], 0x3B, BINS)
        self.facts[at] = np.column_stack((marks, capitals, letters, stop, marks == size, size, toxic, name, shape_bins(chars, size, start, kind)))
        if self.weights is not None:
            self.worth[at] = self.weights[self.facts[at, 7:]].sum(axis=1)
        if self.harmful is not None:
            n = np.fromiter(map(len, parts), np.int64, len(parts))
            bins, part = harm_bins([x for p in parts for x in p])
            self.harm[at, 0] = np.bincount(np.repeat(np.arange(len(parts)), n)[part], self.harmful[bins], minlength=len(parts))
            self.harm[at, 1] = n


def tokenised(texts: pa.Array, facts: Tokens) -> Iterator[tuple[list[list[str]], np.ndarray]]:
    """The tokens of some texts at a time, and the numbers of all of them, which hold until the next are taken."""
    words, n = [], 0
    for text in texts:
        words.append(FIND(text.as_py() or ""))
        n += len(words[-1])
        if n >= CHUNK_TOKENS:
            yield words, facts.numbers([w for ws in words for w in ws])
            words, n = [], 0
    if words:
        yield words, facts.numbers([w for ws in words for w in ws])


def sums_by_text(values: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Sums of the rows of each text; 0 for a text without tokens."""
    out = np.zeros((len(size), *values.shape[1:]), np.float64 if values.dtype.kind == "f" else np.int64)
    some = size > 0
    if some.any():
        out[some] = np.add.reduceat(values, (np.cumsum(size) - size)[some], axis=0, dtype=out.dtype)
    return out


def signals(words: list[list[str]], at: np.ndarray, facts: Tokens) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The signals of texts, whether they have a toxic token, and their sizes."""
    size = np.fromiter(map(len, words), np.int64, len(words))
    marks, capitals, letters, stop, bare, chars, toxic = sums_by_text(facts.facts[at, :7], size).T
    n = np.maximum(1, size)
    same = np.concatenate(([False], at[1:] == at[:-1])) if len(at) else np.empty(0, bool)
    same[(np.cumsum(size) - size)[size > 0]] = False
    distinct = np.fromiter((len(set(ws)) for ws in words), np.int64, len(words))
    stutter = sums_by_text(same.astype(np.int64), size)
    return np.column_stack((marks / np.maximum(1, chars), capitals / np.maximum(1, letters), distinct / n, stop / n, stutter / n, bare / n)), toxic > 0, size


def votes(x: list[float], n: int) -> tuple[int, ...]:
    """1 good, -1 bad, 0 nothing for each labeller; a text of under 10 words gets no vote on its mixture of words."""
    out = []
    for (name, good, bad), v in zip(LABELLERS, x, strict=True):
        silent = n == 0 or n < 10 and name in ("variety", "function_words", "stutter")
        out.append(0 if silent else 1 if good[0] <= v <= good[1] else -1 if bad[0] <= v <= bad[1] else 0)
    return tuple(out)


def posteriors(patterns: np.ndarray, counts: np.ndarray, rounds: int = 60) -> tuple[np.ndarray, dict]:
    """P(good) of each vote pattern, and the fitted model, by expectation-maximisation from the majority vote."""
    counts = counts.astype(float)
    p = np.clip(0.5 + patterns.sum(axis=1) / (2 * max(1, patterns.shape[1])), 0.02, 0.98)
    for _ in range(rounds):
        mass = np.stack((counts * (1 - p), counts * p))
        prior = (mass.sum(axis=1) + 1) / (counts.sum() + 2)
        rates = np.stack([(mass @ (patterns == v) + 1) / (mass.sum(axis=1, keepdims=True) + 3) for v in (-1, 0, 1)])  # vote, class, labeller
        log = np.log(prior)[:, None] + sum(np.log(rates[v + 1]) @ (patterns == v).T for v in (-1, 0, 1))
        p = 1 / (1 + np.exp(np.clip(log[0] - log[1], -500, 500)))
    accuracy = {s: float((prior[1] * rates[2, 1, j] + prior[0] * rates[0, 0, j]) / max(1e-9, 1 - (prior[0] * rates[1, 0, j] + prior[1] * rates[1, 1, j]))) for j, s in enumerate(SIGNALS)}
    return p, {"prior_good": float(prior[1]), "accuracy": accuracy}


def fit_scorer(docs: list[tuple[list[int], list[float], list[float]]], target: np.ndarray, rounds: int = 120, rate: float = 0.5, ridge: float = 1e-4, bins: int = BINS) -> np.ndarray:
    """Weights of the hashed features, the signals and a bias, by full-batch adaptive gradient descent."""
    idx = np.concatenate([np.asarray(d[0], np.int64) for d in docs])
    val = np.concatenate([np.asarray(d[1]) for d in docs])
    row = np.repeat(np.arange(len(docs)), [len(d[0]) for d in docs])
    dense = np.column_stack((np.array([d[2] for d in docs]), np.ones(len(docs))))
    w, past = np.zeros(bins + dense.shape[1]), np.full(bins + dense.shape[1], 1e-8)
    for _ in range(rounds):
        z = np.bincount(row, val * w[idx], minlength=len(docs)) + dense @ w[bins:]
        err = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - target) / len(docs)
        grad = np.concatenate((np.bincount(idx, val * err[row], minlength=bins), dense.T @ err)) + ridge * w
        past += grad**2
        w -= rate * grad / np.sqrt(past)
    return w


def described(fraction: float):
    """text to (votes, idx, val, signals); features only for the sampled share, picked by the hash column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        facts = Tokens()
        for batch in batches:
            rows, drawn = [], iter(batch.column("h").to_pylist())
            for words, at in tokenised(batch.column("text"), facts):
                found, _, size = signals(words, at, facts)
                end = 0
                for x, n in zip(found.tolist(), size.tolist(), strict=True):
                    h, end = next(drawn), end + n
                    idx, val = [], []
                    if n and h is not None and h < fraction:
                        bins, times = np.unique(facts.facts[at[end - n : end], 7:], return_counts=True)
                        idx, val = bins.tolist(), (times / n).tolist()
                    rows.append((",".join(map(str, votes(x, n))), idx, val, x))
            cols = zip(*rows, strict=True) if rows else [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.string(), pa.list_(pa.int64()), pa.list_(pa.float64()), pa.list_(pa.float64())), strict=True)], ["votes", "idx", "val", "signals"])

    return run


def train(docs: DataFrame, text_col: str = "text", sample_docs: int = SAMPLE_DOCS) -> dict:
    """The model: weights, and what EM found. Labellers vote on all documents; the scorer sees about sample_docs of them.

    At most 3 ** 6 vote patterns and about sample_docs feature rows come to the driver.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(text.alias("text"), (F.pmod(F.xxhash64(text), F.lit(1 << 30)) / F.lit(float(1 << 30))).alias("h"))
    kinds = "votes string, idx array<bigint>, val array<double>, signals array<double>"
    found = rows.select("text", F.lit(None).cast("double").alias("h")).mapInArrow(described(0.0), kinds).groupBy("votes").agg(F.count(F.lit(1)).alias("n")).collect()
    found = sorted((tuple(map(int, r["votes"].split(","))), r["n"]) for r in found)
    if not found:
        return {"weights": np.zeros(BINS + len(SIGNALS) + 1), "prior_good": 0.5, "accuracy": {}, "patterns": {}}
    patterns = np.array([p for p, _ in found])
    good, model = posteriors(patterns, np.array([n for _, n in found]))
    share = min(1.0, sample_docs / sum(n for _, n in found))
    sample = rows.where(F.col("h") < share).mapInArrow(described(1.0), kinds).limit(4 * sample_docs).collect()
    model["patterns"] = {",".join(map(str, p)): float(g) for (p, _), g in zip(found, good, strict=True)}
    model["weights"] = fit_scorer([(r["idx"], r["val"], r["signals"]) for r in sample], np.array([model["patterns"][r["votes"]] for r in sample])) if sample else np.zeros(BINS + len(SIGNALS) + 1)
    return model


def harm_features(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Bins of a text's words and their values, which depend on the share of the words that have them."""
    ws = PARTS(text.lower())
    times = Counter(ws)
    bins, word = harm_bins(list(times))
    bins, at = np.unique(bins, return_inverse=True)
    counts = np.bincount(at, np.fromiter(times.values(), np.float64, len(times))[word], minlength=len(bins))
    return bins, counts.astype(np.float32) * np.float32(harm_scale(len(ws)))


def harm_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(text, toxic) to (bin, toxic documents, clean documents) of the task; the last bin counts documents."""
    seen = np.zeros((2, HARM_BINS + 1), np.int64)
    for batch in batches:
        for text, bad in zip(batch.column("text"), batch.column("toxic").to_pylist(), strict=True):
            seen[int(not bad), harm_features(text.as_py() or "")[0]] += 1
            seen[int(not bad), HARM_BINS] += 1
    at = np.flatnonzero(seen.any(axis=0))
    yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), *(pa.array(c[at], pa.int64()) for c in seen)], ["bin", "toxic", "clean"])


def harm_rows(chosen: np.ndarray):
    """(text, toxic) to (toxic, idx, val): the chosen features of each text, packed as 32-bit numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            idx, val = [], []
            for text in batch.column("text"):
                i, v = harm_features(text.as_py() or "")
                live = chosen[i]
                idx.append(i[live].tobytes())
                val.append(v[live].tobytes())
            yield pa.RecordBatch.from_arrays([batch.column("toxic"), pa.array(idx, pa.binary()), pa.array(val, pa.binary())], ["toxic", "idx", "val"])

    return run


def fit_toxic(docs: DataFrame, labels: DataFrame, sample_docs: int = LABELLED_DOCS, id_col: str = "doc_id", text_col: str = "text") -> np.ndarray | None:
    """Weights of HARM_BINS features and a bias; null if the labelled rows are all toxic or all clean.

    Features that two toxic documents have, and toxic ones at more than twice the rate of clean ones, are fitted; the others
    weigh nothing. Labels with a null id or null toxic are left out. At most HARM_BINS + 1 counts and the chosen features of
    the bounded sample come to the driver.
    """
    named = labels.where(F.col("toxic").isNotNull() & F.col(id_col).isNotNull())
    share = min(1.0, sample_docs / max(1, named.count()))
    # The sample's size is bounded by the parameter, so it may be sent to all executors.
    sample = named.where(F.pmod(F.xxhash64(id_col), F.lit(1 << 20)) < F.lit(share * (1 << 20))).limit(2 * sample_docs).select(F.col(id_col).alias("_id"), (F.col("toxic") == 1).alias("toxic"))
    texts = docs.select(F.col(id_col).alias("_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).join(F.broadcast(sample), "_id").select("text", "toxic")
    texts = publish(texts, "labelled")
    found = texts.mapInArrow(harm_counts, "bin long, toxic long, clean long").groupBy("bin").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean")).collect()
    seen = np.zeros((2, HARM_BINS + 1))
    for r in found:
        seen[:, r["bin"]] = r["toxic"], r["clean"]
    (toxic, clean), (n_toxic, n_clean) = seen[:, :HARM_BINS], seen[:, HARM_BINS]
    if not n_toxic or not n_clean:
        return None
    chosen = (toxic >= 2) & ((toxic + 0.5) / (n_toxic + 1) > 2 * (clean + 0.5) / (n_clean + 1))
    rows = sorted((r["toxic"], bytes(r["idx"]), bytes(r["val"])) for r in texts.mapInArrow(harm_rows(chosen), "toxic boolean, idx binary, val binary").collect())
    return fit_scorer([(np.frombuffer(i, np.int32), np.frombuffer(v, np.float32), []) for _, i, v in rows], np.array([float(t) for t, _, _ in rows]), bins=HARM_BINS)


def scorer(weights: np.ndarray, harmful: np.ndarray | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        facts = Tokens(frozenset(ABUSE), weights, harmful)
        dense = weights[BINS:]
        for batch in batches:
            score, toxic, seen = [], [], []
            for words, at in tokenised(batch.column("text"), facts):
                x, bad, size = signals(words, at, facts)
                z = sums_by_text(facts.worth[at], size) / np.maximum(1, size) + x @ dense[:-1] + dense[-1]
                score += np.where(size > 0, 1 / (1 + np.exp(-np.clip(z, -30.0, 30.0))), 0.0).tolist()
                if harmful is not None:
                    harm, n = sums_by_text(facts.harm[at], size).T
                    bad |= (size > 0) & (harm * harm_scale(n) + harmful[HARM_BINS] > 0)
                toxic += bad.tolist()
                seen += [",".join(map(str, votes(v, n))) for v, n in zip(x.tolist(), size.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(score, pa.float64()), pa.array(toxic, pa.bool_()), pa.array(seen, pa.string())], ["row", "quality", "toxic", "votes"])

    return run


def classify(docs: DataFrame, labels: DataFrame | None = None, model: dict | None = None, text_col: str = "text", least: float = 0.5) -> DataFrame:
    """(row: struct of all columns, quality, toxic, votes, keep) for every row; keep = quality >= least and not toxic.

    A null, empty or blank text has quality 0 and isn't kept. Repeated rows are rated alike. No rows give no rows; other
    columns pass through whatever their names. Without a model, one is trained on docs; without labels, only the
    listed words are toxic.
    """
    model = model or train(docs, text_col)
    harmful = fit_toxic(docs, labels, text_col=text_col) if labels is not None else None
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(text_col).alias("text"))
    kind = rows.schema["row"].dataType.simpleString()
    out = rows.mapInArrow(scorer(model["weights"], harmful), f"row {kind}, quality double, toxic boolean, votes string")
    return out.withColumn("keep", (F.col("quality") >= least) & ~F.col("toxic"))
