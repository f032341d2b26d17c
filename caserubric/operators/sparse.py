"""BM25 over packed posting lists: a grid of shards of the corpus and slices of the queries, one task each.

Terms are told apart by salted 64-bit hashes; if two terms share one, another salt is taken. A passage is sent as its
distinct codes and their counts, a query as its codes. A task makes the index of its shard, of the asked terms only, and
adds up whole scores for each query, so that nothing is left to bounds. Contributions are rounded to integers before they
are added, and the order of addition doesn't matter.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shared import placed, publish

SHARD_POSTINGS = 6_000_000  # of some 30 bytes while an index is made
LEAST_POSTINGS = 500_000  # below that, a shard isn't split for the sake of idle cores
SLICE_QUERIES, MOST_SLICES = 40_000, 3  # each slice gets all postings, so slices are few; a slice is streamed, of any size
ROW_CELLS = 24_000_000  # of lists that are held as rows over all documents
GROUPS = 256
KNOWN_TERMS, KNOWN_QUERIES = 500_000, 50_000
PACKED = {"kind": "int", "codes": "array<bigint>", "counts": "array<int>", "code": "bigint", "docs": "bigint", "term": "string"}


def coded(keys: list[str], salt: int, count: bool):
    """Rows of keys and tokens t to two kinds of rows.

    Kind 0: the keys and the codes; if count, distinct ones with their counts. Kind 1, for each batch: a term, its code,
    and the number of rows that hold it.
    """

    def code(term: str) -> int:
        return int.from_bytes(hashlib.blake2b(term.encode("utf-8", "surrogatepass"), digest_size=8, salt=salt.to_bytes(8, "little")).digest(), "little", signed=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, int] = {}
        for batch in batches:
            size, _ = lengths(batch.column("t"))
            spelled = batch.column("t").flatten().dictionary_encode()
            terms = spelled.dictionary.to_pylist()
            if len(known) > KNOWN_TERMS:
                known.clear()
            for x in terms:
                if x not in known:
                    known[x] = code(x)
            names = np.array([known[x] for x in terms], np.int64)
            row, at = np.repeat(np.arange(len(size)), size), spelled.indices.to_numpy().astype(np.int64)
            times = np.ones(len(at), np.int32)
            if count and len(at):
                both, n = np.unique(row * len(terms) + at, return_counts=True)
                row, at, times = both // len(terms), both % len(terms), n.astype(np.int32)
            ends = pa.array(np.concatenate(([0], np.cumsum(np.bincount(row, minlength=len(size))))).astype(np.int32))
            none = lambda n, *kinds: [pa.nulls(n, x) for x in kinds]
            lists = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (names[at], times)]
            columns = [*(batch.column(k) for k in keys), pa.array(np.zeros(len(size), np.int32)), *lists, *none(len(size), pa.int64(), pa.int64(), pa.string())]
            yield pa.RecordBatch.from_arrays(columns, [*keys, *PACKED])
            docs = np.bincount(at, minlength=len(terms)).astype(np.int64)
            blank = none(len(terms), *(batch.column(k).type for k in keys))
            columns = [*blank, pa.array(np.ones(len(terms), np.int32)), *none(len(terms), *(x.type for x in lists)), pa.array(names), pa.array(docs), spelled.dictionary]
            yield pa.RecordBatch.from_arrays(columns, [*keys, *PACKED])

    return run


def lengths(lists: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The lists' lengths, 0 for null, and their values."""
    return pc.fill_null(pc.list_value_length(lists), 0).to_numpy().astype(np.int64), lists.flatten()


class Shard:
    """The index of a shard, fed with batches of (ids, lengths, codes, counts)."""

    def __init__(self, code: np.ndarray, idf: np.ndarray, k1: float, b: float, mean: float, common: float):
        order = np.argsort(code)
        self.code, self.idf = code[order], idf[order]
        self.k1, self.b, self.mean, self.common = k1, b, mean, common
        self.parts: list[tuple] = []
        self.n = 0

    def find(self, codes: np.ndarray) -> np.ndarray:
        """The terms' numbers; -1 for unknown ones."""
        if not len(self.code):
            return np.full(len(codes), -1)
        at = np.minimum(np.searchsorted(self.code, codes), len(self.code) - 1)
        return np.where(self.code[at] == codes, at, -1)

    def feed(self, ids: np.ndarray, length: np.ndarray, size: np.ndarray, codes: np.ndarray, counts: np.ndarray) -> None:
        term, doc = self.find(codes), np.repeat(np.arange(len(ids)), size)
        asked = term >= 0
        term, doc, c = term[asked], doc[asked], counts[asked].astype(np.int64)
        part = c * (self.k1 + 1) / (c + self.k1 * ((1 - self.b) + self.b * length[doc] / self.mean))
        v = np.floor(self.idf[term] * part * 1000 + 0.5)
        self.parts.append((ids, term.astype(np.int32), (doc + self.n).astype(np.int32), v.astype(np.int32)))
        self.n += len(ids)

    def close(self) -> None:
        """Documents get numbers in the order of their ids, so that ties fall to the smaller one."""
        ids, term, doc, v = (np.concatenate([x[j] for x in self.parts]) if self.parts else np.empty(0, np.int64 if not j else np.int32) for j in range(4))
        self.parts.clear()
        self.ids, number = np.unique(ids, return_inverse=True)
        key = (term.astype(np.int64) << 32) | number[doc]
        del term, doc
        order = np.argsort(key)
        key, v = key[order], v[order]
        del order
        new = np.concatenate(([True], key[1:] != key[:-1])) if len(key) else np.empty(0, bool)
        if not new.all():  # an id with several lengths
            first = np.flatnonzero(new)
            key, v = key[first], np.add.reduceat(v, first)
        self.key, self.v = key, v
        self.doc = (key & 0xFFFFFFFF).astype(np.int32)
        self.start = np.searchsorted(key, np.arange(len(self.code) + 1, dtype=np.int64) << 32)
        held = np.diff(self.start)
        long = np.flatnonzero(held > self.common * len(self.ids))
        self.rows: dict[int, np.ndarray] = {}
        self.wide = 0
        for t in long[np.argsort(-held[long], kind="stable")].tolist():
            if (len(self.rows) + 1) * len(self.ids) > ROW_CELLS:
                break
            row = self.rows[t] = np.zeros(len(self.ids), np.int32)
            row[self.doc[self.start[t] : self.start[t + 1]]] = self.v[self.start[t] : self.start[t + 1]]
        self.bounds = self.start.tolist()

    def room(self, k: int) -> None:
        """Scores, padded to groups; the k-th best of the groups' maxima is a floor of what ranks."""
        self.groups = max(GROUPS, 2 * k)
        self.scores = np.zeros(-(-max(1, len(self.ids)) // self.groups) * self.groups, np.int32)

    def top_k(self, terms: list[int], k: int) -> tuple[np.ndarray, np.ndarray]:
        """Numbers and scores of the k best documents that hold one of the terms."""
        sums = self.scores if len(terms) < 10_000 else self.scores.astype(np.int64)
        sums.fill(0)
        whole, doc, v, bounds = sums[: len(self.ids)], self.doc, self.v, self.bounds
        for t in terms:
            row = self.rows.get(t)
            if row is not None:
                whole += row
            else:
                lo, hi = bounds[t], bounds[t + 1]
                whole[doc[lo:hi]] += v[lo:hi]
        floor = np.partition(sums.reshape(-1, self.groups).max(axis=0), self.groups - k)[self.groups - k]
        if floor > 0:
            live = np.flatnonzero(whole >= floor)
        else:  # fewer than k scores above 0, which documents can have that hold a term
            live = np.unique(np.concatenate([doc[bounds[t] : bounds[t + 1]] for t in terms])).astype(np.int64)
        best = live[np.argsort(-whole[live], kind="stable")[:k]]
        return best, whole[best]

    def holds(self, term: np.ndarray, doc: np.ndarray) -> np.ndarray:
        key = (term << 32) | doc
        at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
        return self.key[at] == key


def shard_search(qid: list[str], k: int, k1: float, b: float, mean: float, common: float):
    """Rows sorted by (cell, kind): asked terms with their weights, kind 0, passages, 1, and queries, 2. Gives one row a query."""

    def column(batch: pa.RecordBatch, name: str) -> np.ndarray:
        return batch.column(name).to_numpy(zero_copy_only=False)

    def flat(batch: pa.RecordBatch, name: str) -> tuple[np.ndarray, np.ndarray]:
        size, values = lengths(batch.column(name))
        return size, values.to_numpy(zero_copy_only=False)

    def answer(shard: Shard, batch: pa.RecordBatch, seen: dict) -> pa.RecordBatch:
        size, codes = flat(batch, "codes")
        own = column(batch, "own")
        term = shard.find(codes)
        live = (term >= 0) & (np.diff(shard.start)[term] > 0) if len(shard.key) else np.zeros(len(term), bool)
        query = np.repeat(np.arange(len(size)), size)
        place = np.arange(len(codes)) - np.repeat(np.cumsum(size) - size, size)
        weighty = live & (place < own[query])
        found = np.full((len(size), k), -1, np.int64)
        score = np.zeros((len(size), k), np.int64)
        ends = np.cumsum(np.bincount(query[live], minlength=len(size))).tolist()
        terms, lo = term[live].tolist(), 0
        for i, hi in enumerate(ends):
            if hi > lo:
                name = tuple(terms[lo:hi])
                best = seen.get(name)
                if best is None:
                    if len(seen) > KNOWN_QUERIES:
                        seen.clear()
                    best = seen[name] = shard.top_k(terms[lo:hi], k)
                found[i, : len(best[0])], score[i, : len(best[0])] = best
                lo = hi
        t, q = term[weighty], query[weighty]
        shared = np.zeros((len(size), k), np.int64)
        if len(t):
            hit = shard.holds(np.repeat(t, k), np.maximum(found[q], 0).ravel()).reshape(-1, k) & (found[q] >= 0)
            np.add.at(shared, q, hit)
        there = found >= 0
        n = there.sum(axis=1)
        some = np.flatnonzero(n)
        stops = pa.array(np.concatenate(([0], np.cumsum(n[some]))).astype(np.int32))
        as_list = lambda x: pa.ListArray.from_arrays(stops, pa.array(x))
        out = {c: batch.column(c).take(pa.array(some)) for c in qid}
        ids = shard.ids[found[there]] if len(shard.ids) else np.empty(0, np.int64)
        return pa.RecordBatch.from_pydict(out | {"_minus": as_list(-score[there]), "_doc": as_list(ids), "_shared": as_list(shared[there])})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, shard, words, ready, seen = None, None, [], False, {}
        for batch in batches:
            if not batch.num_rows:
                continue
            both = column(batch, "cell") * 3 + column(batch, "kind")
            cuts = [0, *(np.flatnonzero(both[1:] != both[:-1]) + 1).tolist(), len(both)]
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                now, kind, part = both[lo] // 3, both[lo] % 3, batch.slice(lo, hi - lo)
                if now != cell:
                    cell, shard, words, ready, seen = now, None, [], False, {}
                if kind == 0:
                    words.append((flat(part, "codes")[1], flat(part, "idf")[1]))
                    continue
                if shard is None:
                    code, idf = (np.concatenate([w[j] for w in words]) if words else np.empty(0, np.int64 if not j else float) for j in range(2))
                    shard, words = Shard(code, idf, k1, b, mean, common), []
                if kind == 1:
                    size, codes = flat(part, "codes")
                    shard.feed(column(part, "doc_id"), column(part, "len"), size, codes, flat(part, "counts")[1])
                    continue
                if not ready:
                    shard.close()
                    shard.room(k)
                    ready = True
                yield answer(shard, part, seen)

    return run


def pack(df: DataFrame, salt: int, count: bool, label: str) -> DataFrame:
    """df with its tokens t as codes, and the terms, published."""
    keys = [c for c in df.columns if c != "t"]
    fields = [*(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keys), *(f"{c} {x}" for c, x in PACKED.items())]
    return publish(df.mapInArrow(coded(keys, salt, count), ", ".join(fields)), label)


def top_k(queries: DataFrame, corpus: DataFrame, qid: list[str], k: int, k1: float, b: float, common: float) -> DataFrame:
    """qid, doc_id, rank, score (in thousandths), shared, from (qid, own, t) and (doc_id, t).

    t are tokens, a query's distinct ones. shared tells how many of a query's first `own` tokens the passage holds. Ids are
    whole numbers; passages of the same id and length are one. common: the share of a shard's documents from which a list
    is held as a row over all of them.
    """
    spark = queries.sparkSession
    corpus = corpus.withColumn("len", F.size("t"))
    salt, facts = 0, None
    while True:
        packed = pack(corpus, salt, True, "passages")
        docs = packed.where("kind = 0")
        if facts is None:
            facts = docs.agg(F.count(F.lit(1)).alias("n"), F.avg("len").alias("mean"), F.count_distinct("doc_id").alias("ids")).first()
            if facts["ids"] < facts["n"]:
                corpus = corpus.where("doc_id is not null").groupBy("doc_id", "len").agg(F.flatten(F.collect_list("t")).alias("t"))
                continue
        asked = pack(queries, salt, False, "asked")
        terms = packed.where("kind = 1").select("code", "term", "docs", F.lit(0).alias("asked"))
        terms = terms.union(asked.where("kind = 1").select("code", "term", F.lit(0).cast("long"), F.lit(1)))
        vocabulary = publish(terms.groupBy("code", "term").agg(F.sum("docs").alias("d"), F.max("asked").alias("asked")), "vocabulary")
        if not vocabulary.groupBy("code").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count():
            break
        salt += 1
    asked = asked.where("kind = 0 and size(codes) > 0")
    sizes = docs.agg(F.sum(F.size("codes"))).first()[0] or 0, asked.count(), vocabulary.where("asked = 1 and d > 0").count()
    slices = min(MOST_SLICES, max(1, -(-sizes[1] // SLICE_QUERIES)))
    shards = max(1, -(-sizes[0] // SHARD_POSTINGS), min(-(-sizes[0] // LEAST_POSTINGS), -(-spark.sparkContext.defaultParallelism // slices)))
    cells = shards * slices
    places = F.array(*(F.lit(x).cast("long") for x in placed(spark, cells)))
    idf = F.log(1 + (F.lit(facts["n"]) - F.col("d") + F.lit(0.5)) / (F.col("d") + F.lit(0.5)))
    words = vocabulary.where("asked = 1 and d > 0").select("code", idf.alias("w")).groupBy(F.pmod("code", F.lit(-(-max(1, sizes[2]) // 50_000)))).agg(F.collect_list(F.struct("code", "w")).alias("x"))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    shard, slice_ = F.pmod(F.xxhash64("doc_id"), F.lit(shards)), F.pmod(F.xxhash64(*qid), F.lit(slices))
    rows = [
        words.select("x", every(cells).alias("cell")).select("cell", F.lit(0).alias("kind"), F.col("x.code").alias("codes"), F.col("x.w").alias("idf")),
        docs.where("size(codes) > 0").select("doc_id", "len", "codes", "counts", every(slices).alias("_s")).select((shard * slices + F.col("_s")).cast("int").alias("cell"), F.lit(1).alias("kind"), "doc_id", "len", "codes", "counts"),
        asked.select(*qid, "own", "codes", every(shards).alias("_s")).select((F.col("_s") * slices + slice_).cast("int").alias("cell"), F.lit(2).alias("kind"), *qid, "own", "codes"),
    ]
    both = rows[0].unionByName(rows[1], allowMissingColumns=True).unionByName(rows[2], allowMissingColumns=True)
    dealt = both.withColumn("_place", F.get(places, F.col("cell"))).repartition(cells, "_place").drop("_place").sortWithinPartitions("cell", "kind")
    kinds = [*(f"`{c}` {queries.schema[c].dataType.simpleString()}" for c in qid), "_minus array<bigint>", "_doc array<bigint>", "_shared array<bigint>"]
    found = dealt.mapInArrow(shard_search(qid, k, k1, b, facts["mean"] or 1.0, common), ", ".join(kinds))
    hits = found.select(*qid, F.arrays_zip("_minus", "_doc", "_shared").alias("hits"))
    if shards > 1:
        hits = hits.groupBy(*qid).agg(F.slice(F.sort_array(F.flatten(F.collect_list("hits"))), 1, k).alias("hits"))
    each = hits.select(*qid, F.posexplode("hits").alias("_at", "_hit"))
    found = each.select(*qid, F.col("_hit._doc").alias("doc_id"), (-F.col("_hit._minus")).alias("score"), (F.col("_at") + 1).alias("rank"), F.col("_hit._shared").alias("shared"))
    return publish(found, "hits")  # a search runs once and leaves no shuffle files, however often its hits are read
