"""N-gram Jaccard join with parity sketches.

A document is the set of its word shingles, hashed to 64 bits. For a band of set sizes, D bounds the symmetric
difference of any linked pair. Hashing shingles to G > D segments and XOR-ing the shingles of each segment gives a
parity sketch: a differing shingle changes one segment, so the number of differing segments, and the Hamming distance
of the bit form, never exceed the symmetric difference. By the pigeonhole a linked pair agrees in at least G - D
segments, so joining on (band, segment, value) finds it. What is found is checked against a 1024-bit parity sketch,
then exactly.

Equal sets are one class, and only classes are joined. Buckets first give stars only; classes that verified stars
connect need no further comparison, and just pairs of a bucket that are still in different components are tried.

Whole texts are cut into shingles once; only the classes of candidate pairs are cut again, for the exact check.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import components, join_facts, publish
from .repeats import hashed_runs

SKETCH_WORDS = 16  # of 64 bits
SENT_CLASSES = 100_000  # classes whose sketches, some 15 MB, may be sent to all executors; more are joined by shuffles
HUB_PAIRS = 1000  # pairs that are checked exactly by one class's set in a part
KEY_WORDS = 1 << 20  # words of 64 bits of the bitmap that tells which texts are wanted


@dataclass(frozen=True)
class Overlap:
    """Shingles of `width` words, linked when den * intersection >= num * union."""

    width: int = 5
    num: int = 80
    den: int = 100

    def most(self, total):
        """The largest symmetric difference of a linked pair whose sizes add up to total."""
        return (self.den - self.num) * total // (self.den + self.num)

    @cached_property
    def tops(self) -> list[int]:
        """The largest set size of each band; linked pairs are in one band or in neighbours."""
        out = [1]
        while out[-1] < 1 << 40:
            out.append((out[-1] + 1) * self.den // self.num)
        return out

    def segments(self, band: int) -> tuple[int, int]:
        """(G, D) for pairs whose smaller set is in the band."""
        top = self.tops[band]
        d = self.most(top + top * self.den // self.num)
        return d + 1 + (max(1, d // 8) if d > 1 else 0), d


def mixed(x: np.ndarray, salt: int) -> np.ndarray:
    x = (x ^ np.uint64(salt)) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


class ByteCodes(dict):
    """64-bit hash of a word in UTF-8, remembered for up to a million words."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 1_000_000:
            self.clear()
        code = self[word] = xxhash.xxh64_intdigest(word)
        return code


def shingles(raw: bytes, codes: ByteCodes, width: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word runs of a UTF-8 text; the whole sequence as one if it is shorter.

    Methods of bytes know ASCII only: lower() changes A-Z, and split() cuts at 0x20 and 0x09 to 0x0D.
    """
    ws = raw.lower().split()
    if not ws:
        return np.empty(0, np.uint64)
    c = np.fromiter(map(codes.__getitem__, ws), np.uint64, len(ws))
    short = len(ws) < width
    return np.unique(hashed_runs(c, min(width, len(ws))) ^ np.uint64(len(ws) if short else 0))


def set_name(value: np.ndarray) -> tuple[int, int]:
    """128-bit name of a set, from the mixed values of its shingles."""
    both = np.array([np.bitwise_xor.reduce(value), np.add.reduce(value)])
    return tuple(mixed(both, 0x51ED + len(value)).astype(np.int64).tolist())


def parity_bits(value: np.ndarray) -> np.ndarray:
    odd = (np.bincount((value >> np.uint64(54)).astype(np.int64), minlength=64 * SKETCH_WORDS) & 1).astype(np.uint8)
    return np.packbits(odd, bitorder="little").view(np.int64)


def segment_keys(s: np.ndarray, value: np.ndarray, rule: Overlap) -> np.ndarray:
    """Join keys of one sorted set and its mixed values, for its own band and for the band below.

    Segments are ranges of the shingles' hashes. Those of at most one shingle carry no key when there are fewer of them
    than segments that any linked pair shares; a shared segment has equal shingles on both sides, so the pair still meets
    in another one.
    """
    band = int(np.searchsorted(rule.tops, len(s)))
    high = s >> np.uint64(32)
    out = []
    for b in (band, band - 1):
        if b < 0:
            continue
        g, d = rule.segments(b)
        if not d:
            continue  # only equal sets can be linked there
        seg = (high * np.uint64(g)) >> np.uint64(32)
        first = np.flatnonzero(np.concatenate(([True], seg[1:] != seg[:-1])))
        xor, count, name = np.bitwise_xor.reduceat(value, first), np.diff(np.append(first, len(seg))), seg[first]
        empty, single = g - len(name), int((count == 1).sum())
        if empty + single < g - d:
            xor, name = xor[count > 1], name[count > 1]
        elif empty >= g - d:
            bare = np.setdiff1d(np.arange(g, dtype=np.uint64), name)
            xor, name = np.append(xor, np.zeros(len(bare), np.uint64)), np.append(name, bare)
        out.append(mixed(xor, 0x111) ^ mixed(name + np.uint64(b << 40), 0x222))
    return np.concatenate(out).view(np.int64) if out else np.empty(0, np.int64)


DESCRIBED = "k1 long, k2 long, name long, tag long, n long, bits array<bigint>, keys array<bigint>"


def describe(rule: Overlap):
    """(row, k1, k2, text) to (row, k1, k2, name, tag, n, bits, keys), in one pass over the texts.

    name is null and bits and keys are empty for a document without words. Keys come with the document that a task meets
    first of a class, so exact copies leave a task once.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes, met = ByteCodes(), set()
        none = np.empty(0, np.int64)
        for batch in batches:
            names, tags, sizes, bits, keys = [], [], [], [], []
            for text in batch.column("text").cast(pa.binary()):
                s = shingles(text.as_py(), codes, rule.width)
                value = mixed(s, 0x7A1)
                name = set_name(value) if len(s) else (None, None)
                names.append(name[0])
                tags.append(name[1])
                sizes.append(len(s))
                bits.append(parity_bits(value) if len(s) else none)
                if not len(s) or name in met:
                    keys.append(none)
                    continue
                if len(met) < 1_000_000:
                    met.add(name)
                keys.append(segment_keys(s, value, rule))
            longs = lambda x: pa.array(x, pa.int64())
            lists = lambda x: pa.array(x, pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column("row"), batch.column("k1"), batch.column("k2"), longs(names), longs(tags), longs(sizes), lists(bits), lists(keys)], ["row", "k1", "k2", "name", "tag", "n", "bits", "keys"])

    return run


def whole_groups(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.Table]:
    """Batches sorted by key, cut so that no group spans two of them."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        k = batch.column(key).to_numpy(zero_copy_only=False)
        cut = int(np.searchsorted(k, k[-1]))
        if cut:
            yield pa.Table.from_batches([*held, batch.slice(0, cut)])
            held = []
        elif held and held[-1].column(key)[-1].as_py() != k[0]:
            yield pa.Table.from_batches(held)
            held = []
        held.append(batch.slice(cut))
    if held:
        yield pa.Table.from_batches(held)


def wide_buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, name) sorted by both, to (key, name, size) for buckets of two names or more."""
    for t in whole_groups(batches, "key"):
        key, name = (t.column(c).to_numpy() for c in ("key", "name"))
        fresh = np.concatenate(([True], (key[1:] != key[:-1]) | (name[1:] != name[:-1])))
        key, name = key[fresh], name[fresh]
        first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        size = np.diff(np.append(first, len(key)))
        size = np.repeat(size, size)
        out = [x[size > 1] for x in (key, name, size)]
        for lo in range(0, len(out[0]), 50_000):
            yield pa.RecordBatch.from_arrays([pa.array(x[lo : lo + 50_000]) for x in out], ["key", "name", "size"])


def stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, name, met) sorted by key and name, to (key, name, leader, other): two classes with which the others are compared.

    The leader has the largest `met`, the number of classes that it meets in all its buckets: the middle of a family
    agrees with more of it than its outlying classes do. The other is drawn by one of four orders, by bucket.
    """
    for t in whole_groups(batches, "key"):
        key, name, met = (t.column(c).to_numpy() for c in ("key", "name", "met"))
        first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        size = np.diff(np.append(first, len(key)))
        lot = mixed(name.view(np.uint64), 0x1EAD)
        leaders = []
        for rank in ((met.view(np.uint64) << np.uint64(24)) ^ (lot >> np.uint64(40)), lot ^ ((key.view(np.uint64) & np.uint64(3)) << np.uint64(62))):
            lead = np.where(rank == np.repeat(np.maximum.reduceat(rank, first), size), name, np.iinfo(np.int64).min)
            leaders.append(np.repeat(np.maximum.reduceat(lead, first), size))
        for lo in range(0, len(key), 50_000):
            yield pa.RecordBatch.from_arrays([pa.array(x[lo : lo + 50_000]) for x in (key, name, *leaders)], ["key", "name", "leader", "other"])


def close_pairs(rule: Overlap):
    """(key, name, root, n, bits) sorted by key, to pairs (a, b) of a bucket that may be linked and aren't connected yet.

    Rows are compared with the d-th row after them, for all d within the largest bucket, as whole columns.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met: set[tuple[int, int]] = set()
        for t in whole_groups(batches, "key"):
            key, name, root, n = (t.column(c).to_numpy() for c in ("key", "name", "root", "n"))
            flat = t.column("bits").combine_chunks()
            bits = flat.flatten().to_numpy().view(np.uint64).reshape(-1, SKETCH_WORDS)
            out: list[np.ndarray] = []
            at, d = np.arange(len(key)), 1
            while True:
                at = at[at + d < len(key)]
                at = at[key[at] == key[at + d]]
                if not len(at):
                    break
                for lo in range(0, len(at), 65536):
                    x = at[lo : lo + 65536]
                    x = x[root[x] != root[x + d]]
                    small, large = np.minimum(n[x], n[x + d]), np.maximum(n[x], n[x + d])
                    x = x[small * rule.den >= large * rule.num]
                    x = x[np.bitwise_count(bits[x] ^ bits[x + d]).sum(axis=1) <= rule.most(n[x] + n[x + d])]
                    out.append(np.stack((np.minimum(name[x], name[x + d]), np.maximum(name[x], name[x + d])), axis=1))
                d += 1
            fresh = [p for p in map(tuple, np.unique(np.concatenate(out), axis=0).tolist()) if p not in met] if out else []
            if len(met) < 500_000:
                met.update(fresh)
            yield pa.RecordBatch.from_arrays([pa.array([p[j] for p in fresh], pa.int64()) for j in (0, 1)], ["a", "b"])

    return run


def sets_of(rule: Overlap):
    """(name, text, to) to (name, shingles, to)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = ByteCodes()
        for batch in batches:
            sets = [shingles(x.as_py(), codes, rule.width) for x in batch.column("text").cast(pa.binary())]
            yield pa.RecordBatch.from_arrays([batch.column("name"), pa.array([s.tobytes() for s in sets], pa.binary()), batch.column("to")], ["name", "shingles", "to"])

    return run


def linked(rule: Overlap):
    """(hub, part, member, name, shingles) sorted by the first three, to the linked pairs (a, b); the hub's own set comes first in each part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, own = None, np.empty(0, np.uint64)
        for batch in batches:
            out = []
            for hub, part, member, name, raw in zip(*(batch.column(c).to_pylist() for c in ("hub", "part", "member", "name")), batch.column("shingles"), strict=True):
                s = np.frombuffer(raw.as_py(), np.uint64)
                if not member:
                    at, own = (hub, part), s
                    continue
                if at != (hub, part):
                    raise ValueError(f"class {hub} has no set")
                both = len(np.intersect1d(own, s, assume_unique=True))
                if rule.den * both >= rule.num * (len(own) + len(s) - both):
                    out.append((min(hub, name), max(hub, name)))
            yield pa.RecordBatch.from_arrays([pa.array([x[j] for x in out], pa.int64()) for j in (0, 1)], ["a", "b"])

    return run


def perhaps_among(rows: DataFrame, wanted: DataFrame) -> DataFrame:
    """rows without most of those whose (k1, k2) isn't wanted, by a bitmap of KEY_WORDS words at most, which is broadcast."""
    bit = F.expr("shiftleft(1L, cast(k2 & 63 as int))")
    word = F.pmod("k1", F.lit(KEY_WORDS))
    bitmap = wanted.groupBy(word.alias("_word")).agg(F.bit_or(bit).alias("_bits"))
    return rows.join(F.broadcast(bitmap), word == F.col("_word")).where(F.col("_bits").bitwiseAND(bit) != 0).drop("_word", "_bits")


def sketches(classes: DataFrame) -> DataFrame:
    """(name, n, bits), marked for broadcast if there are few."""
    light = classes.select("name", "n", "bits")
    return F.broadcast(light) if classes.count() <= SENT_CLASSES else light


def verified(pairs: DataFrame, rows: DataFrame, classes: DataFrame, rule: Overlap) -> DataFrame:
    """The linked ones of pairs (a, b): sizes and 1024-bit sketches first, then the sets themselves."""
    light = sketches(classes)
    side = lambda s: light.select(F.col("name").alias(s), F.col("n").alias(f"n{s}"), F.col("bits").alias(f"bits{s}"))
    far = F.aggregate(F.zip_with("bitsa", "bitsb", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
    near = pairs.join(side("a"), "a").join(side("b"), "b").where((F.least("na", "nb") * rule.den >= F.greatest("na", "nb") * rule.num) & (far <= F.floor((rule.den - rule.num) * (F.col("na") + F.col("nb")) / (rule.den + rule.num))))
    near = publish(near.select("a", "b"), "near")
    # each pair meets at the end that has more pairs, its hub; parts of a hub hold some HUB_PAIRS pairs each
    ends = near.select(F.explode(F.array("a", "b")).alias("name")).groupBy("name").agg(F.count(F.lit(1)).alias("n"))
    end = lambda s: ends.select(F.col("name").alias(s), F.col("n").alias(f"n{s}"))
    of_a = F.col("na") >= F.col("nb")
    parts = F.floor(F.greatest("na", "nb") / HUB_PAIRS) + 1
    met = near.join(end("a"), "a").join(end("b"), "b").select(F.when(of_a, F.col("a")).otherwise(F.col("b")).alias("hub"), F.when(of_a, F.col("b")).otherwise(F.col("a")).alias("name"), parts.alias("parts"))
    met = publish(met.select("hub", "name", F.pmod(F.xxhash64("name"), "parts").alias("part")), "met")
    to = lambda member: F.struct("hub", "part", F.lit(member).alias("member")).alias("to")
    sent = met.select("name", to(True)).union(met.select("hub", "part").distinct().select(F.col("hub").alias("name"), to(False)))
    wanted = publish(sent.groupBy("name").agg(F.collect_list("to").alias("to")).join(classes.select("name", "key.k1", "key.k2"), "name"), "wanted")
    texts = perhaps_among(rows.select("k1", "k2", "text"), wanted).join(wanted, ["k1", "k2"]).groupBy("k1", "k2", "name").agg(F.any_value("text").alias("text"), F.any_value("to").alias("to")).select("name", "text", "to")
    sets = texts.mapInArrow(sets_of(rule), "name long, shingles binary, to array<struct<hub: long, part: long, member: boolean>>")
    spread = sets.select("name", "shingles", F.explode("to").alias("to")).select("to.hub", "to.part", "to.member", "name", "shingles")
    return publish(spread.repartition("hub", "part").sortWithinPartitions("hub", "part", "member").mapInArrow(linked(rule), "a long, b long"), "links")


def near_duplicates(docs: DataFrame, rule: Overlap = Overlap(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, n_shingles, component_id = the smallest id reachable by links, itself included; group and key.

    Words are lower-cased in A-Z only. Null, empty and blank texts have no shingles and link with nothing; a shorter text is one
    shingle, its whole sequence. Repeated rows and equal texts are one class. A null id never is a component's id
    unless nothing else is in it. Other columns are ignored; no rows give no rows.

    group names the component (null without shingles), k1 and k2 the row by id and text. Sets are told apart by 128-bit
    hashes, shingles by 64-bit hashes.
    """
    rows = keyed_rows(docs, id_col, text_col)
    kind = rows.schema["row"].dataType.simpleString()
    named = publish(rows.mapInArrow(describe(rule), f"row {kind}, {DESCRIBED}"), "named")
    classes = classes_of(named)
    if classes.where("lo <> hi").limit(1).count():
        # Two classes share the first 64 bits of their names: all but one of them are renamed by the other 64.
        first = classes.where("lo <> hi").select("name", "lo")
        other = F.col("lo").isNotNull() & (F.col("tag") != F.col("lo"))
        named = publish(named.join(first, "name", "left").withColumn("name", F.when(other, F.xxhash64("name", "tag")).otherwise(F.col("name"))).drop("lo"), "renamed")
        classes = classes_of(named)
    keys = named.where(F.size("keys") > 0).select("name", F.explode("keys").alias("key"))
    by_key = lambda df: df.repartition("key").sortWithinPartitions("key", "name")
    wide = by_key(keys).select("key", "name").mapInArrow(wide_buckets, "key long, name long, size long")
    met = wide.select("key", "name", F.sum("size").over(Window.partitionBy("name")).alias("met"))
    buckets = publish(by_key(met).mapInArrow(stars, "key long, name long, leader long, other long"), "buckets")
    tried = buckets.select("name", F.explode(F.array("leader", "other")).alias("with")).where("name <> with").select(F.least("name", "with").alias("a"), F.greatest("name", "with").alias("b")).distinct()
    links = verified(tried, rows, classes, rule)
    root = publish(components(links), "roots")
    # pairs with a bucket's leader or other have been tried, so only buckets of four and more have pairs left
    member = buckets.where("name <> leader and name <> other").select("key", "name").join(root.withColumnRenamed("id", "name"), "name", "left").withColumn("root", F.coalesce("component", "name"))
    open_keys = member.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("key")
    rest = member.join(open_keys, "key", "left_semi").join(sketches(classes), "name").select("key", "name", "root", "n", "bits")
    more = rest.repartition("key").sortWithinPartitions("key", "name").mapInArrow(close_pairs(rule), "a long, b long").distinct()
    links = links.union(verified(more, rows, classes, rule))
    joined = classes.select("name", "row", "copies").join(publish(components(links), "roots").withColumnRenamed("id", "name"), "name", "left").withColumn("component", F.coalesce("component", "name"))
    joined = publish(joined, "joined")
    least = joined.groupBy("component").agg(F.min("row").alias("component_id"), F.count(F.lit(1)).alias("n"))
    of = join_facts(joined, publish(least, "least"), "component", ["name"])
    of = publish(of.select("name", "component", "component_id", F.col("copies").alias("n")), "of")
    found = join_facts(named.select("row", "k1", "k2", "name", F.col("n").alias("n_shingles")), of, "name", ["k1", "k2"])
    return found.select(F.col("row").alias(id_col), "n_shingles", F.coalesce("component_id", "row").alias("component_id"), F.col("component").alias("group"), "k1", "k2")


def keyed_rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(row: the id, text, k1, k2); the keys are 128 bits of id and text."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select(F.col(id_col).alias("row"), F.xxhash64(F.col(id_col), text).alias("k1"), F.xxhash64(text, F.lit(1), F.col(id_col)).alias("k2"), text.alias("text"))


def classes_of(named: DataFrame) -> DataFrame:
    """(name, lo and hi of its tags, key of a member, its smallest id, number of members, n, bits) of each class."""
    one = named.where("name is not null").groupBy("name")
    return publish(one.agg(F.min("tag").alias("lo"), F.max("tag").alias("hi"), F.min(F.struct("k1", "k2")).alias("key"), F.min("row").alias("row"), F.count(F.lit(1)).alias("copies"), F.first("n").alias("n"), F.first("bits").alias("bits")), "classes")


def one_of_each(docs: DataFrame, rule: Overlap = Overlap(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one row of each component, that of the smallest id; rows without shingles stay. The columns of docs.

    Rows of one id and text are one row, whatever their other columns say; those may have any names.
    """
    found = publish(near_duplicates(docs.select(id_col, text_col), rule, id_col, text_col), "components")
    key = F.struct("k1", "k2")
    first = found.where(F.col("group").isNotNull()).groupBy("group").agg(F.min_by(key, F.struct(F.col(id_col).isNull(), F.col(id_col), key)).alias("key"))
    stay = publish(first.select("key.k1", "key.k2").union(found.where(F.col("group").isNull()).select("k1", "k2")).distinct(), "stay")
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.xxhash64(F.col(id_col), text).alias("k1"), F.xxhash64(text, F.lit(1), F.col(id_col)).alias("k2"))
    return rows.join(stay, ["k1", "k2"], "left_semi").dropDuplicates(["k1", "k2"]).select("row.*")
