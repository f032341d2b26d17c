"""The ten operators against brute force, round trips and edge cases on small fixtures."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from caserubric.llm import mixing, packing, quality, queries, tiff
from caserubric.llm.chat import chat_digest, format_chats, parse_chats
from caserubric.llm.common import components, table
from caserubric.llm.licenses import SENTENCES, license_scan
from caserubric.llm.neardup import Overlap, near_duplicates, one_of_each
from caserubric.llm.repeats import remove_repeats
from caserubric.llm.search import bm25_top_k
from caserubric.llm.warc import read_warc, reachable, warc_round_trip
from conftest import SF

WORDS = re.compile(r"[^\x20\x09-\x0D]+").findall
#: Null and empty texts, blanks, repeated rows, null ids and sources, clashing extra columns.
ODD = [(1, None, "a"), (2, "", None), (3, " \t\n", "a"), (4, "one two", "b"), (4, "one two", "b"), (None, "one two three four five six", "b"), (7, "é\u00a0x " * 3000, None)]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, "doc_id long, text string, source string").withColumns({c: F.lit(9) for c in ("row", "k1", "key", "size", "copies", "name", "shard", "spans")})


@pytest.fixture(scope="module")
def empty(odd):
    return odd.limit(0)


def test_odd_rows_and_empty_tables(spark, odd, empty):
    runs = {
        "license": (license_scan, 7), "tiff": (tiff.store_texts, 7), "pack": (packing.pack, 8), "mix": (mixing.mix, 7),
        "quality": (lambda d: quality.classify(d), 7), "repeats": (remove_repeats, 7), "near": (near_duplicates, 7),
        "warc": (lambda d: warc_round_trip(d, "doc_id", "text", "source"), 7),
    }
    for name, (f, rows) in runs.items():
        assert f(odd).count() == rows, name
        assert f(empty).count() == 0, name
    q = odd.select(F.col("doc_id").alias("query_id"), F.col("text").alias("query"))
    assert {r.query_id for r in bm25_top_k(odd, q).collect()} == {4, 7}
    assert bm25_top_k(empty, q).count() == 0
    chat = odd.select(F.col("doc_id").alias("conv_id"), F.lit(1).alias("turn"), F.col("source").alias("role"), "text", "row")
    assert format_chats(chat).count() == 6 and format_chats(chat.limit(0)).count() == 0
    assert one_of_each(odd).count() == 6


def test_mix_repeats_rows(spark, odd):
    docs = spark.createDataFrame([(k, "w " * (k % 40 + 1), f"s{k % 4}") for k in range(400)], "doc_id long, text string, source string")
    m = mixing.mix(docs)
    rows = m.collect()
    assert rows == mixing.mix(docs).collect() or sorted(rows) == sorted(mixing.mix(docs).collect())
    size, want, got = collections.Counter(), {}, collections.Counter()
    for r in rows:
        assert 0 <= r.taken <= 2 * r.size
        size[r.source] += r.size
        got[r.source] += r.taken
        want[r.source] = r.target
    assert sum(want.values()) == pytest.approx(1.5 * sum(size.values()))
    assert all(abs(got[s] - want[s]) <= 40 and want[s] <= 2 * size[s] + 1e-6 for s in want)
    assert mixing.repeated(docs, m).count() == sum(r.copies for r in rows)


def test_pivot_is_fair_and_keeps_the_words():
    total = np.zeros(6)
    size = np.array([900, 80, 50, 40, 30, 7])
    for k in range(4000):
        p, held = mixing.pivot(size, np.full(6, 0.3), np.random.default_rng(k).random(6))
        assert sum(0 < x < 1 for x in p) == (held >= 0) <= 1 and (size * p).sum() == pytest.approx(0.3 * size.sum())
        total += p
    assert np.allclose(total / 4000, 0.3, atol=0.03)


@pytest.mark.parametrize("compression", [tiff.NONE, tiff.PACKBITS, tiff.LZW, tiff.DEFLATE])
@pytest.mark.parametrize("tile", [0, 16, 48])
def test_tiff_round_trip(compression, tile):
    rng = random.Random(compression + tile)
    for payload in (b" " * 192, rng.randbytes(192 * 7), b"aaab" * 48 * 1030):
        for predictor in (1, 2):
            media = tiff.encode_tiff(payload, compression, predictor, tile)
            assert b"".join(i.tobytes() for _, i in tiff.tiff_images(media)) == payload


def test_tiff_pages_and_faults(spark):
    good = tiff.encode_tiff(bytes(192 * 1500))
    df = spark.createDataFrame([(1, good), (2, good[:-40]), (3, b"junk"), (4, None)], "doc_id long, media binary")
    got = collections.Counter((r.doc_id, r.error is None) for r in tiff.tiff_pages(df).collect())
    assert got[1, True] == 2 and got[2, False] == got[3, False] == got[4, False] == 1


def test_packbits_and_lzw_on_known_bytes():
    """Vectors worked out by hand from the rules of the format, not by this encoder."""
    packed = bytes.fromhex("FEAA0280002AFDAA0380002A22F7AA80")
    assert tiff.packbits_decode(packed) == bytes.fromhex("AAAAAA80002AAAAAAAAA80002A22") + b"\xaa" * 10
    # clear, 7, 258 (7 7), 8, 8, 258, end: nine bits each, the highest bit first
    codes = "".join(f"{c:09b}" for c in (256, 7, 258, 8, 8, 258, 257))
    assert tiff.lzw_decode(int(codes.ljust(64, "0"), 2).to_bytes(8, "big")) == bytes([7, 7, 7, 8, 8, 7, 7])


def test_layout_faults_are_rows(spark):
    import struct

    def broken(tile, tag):
        data = bytearray(tiff.encode_tiff(bytes(192 * 4), tile=tile))
        at = struct.unpack_from("<I", data, 4)[0]
        for k in range(struct.unpack_from("<H", data, at)[0]):
            if struct.unpack_from("<H", data, at + 2 + 12 * k)[0] == tag:
                struct.pack_into("<I", data, at + 10 + 12 * k, 0)
        return bytes(data)

    files = [(1, broken(0, 278)), (2, broken(16, 322)), (3, broken(16, 323)), (4, broken(0, 256)), (5, tiff.encode_tiff(bytes(192)))]
    got = {r.doc_id: r.error for r in tiff.tiff_pages(spark.createDataFrame(files, "doc_id long, media binary")).collect()}
    assert got.pop(5) is None and len(got) == 4 and all(got.values())


def test_packing_is_the_same_in_every_layout(spark):
    rows = [(k % 300, f"w{k % 300} " * (k % 40), f"s{k % 5}") for k in range(900)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    runs = [sorted(map(repr, packing.pack(docs.repartition(n), capacity=50).collect())) for n in (1, 7)]
    assert runs[0] == runs[1]


def test_best_fit_against_trying_every_bin():
    rng = random.Random(8)
    for _ in range(30):
        n = 60
        sizes = sorted((rng.randrange(1, 40) for _ in range(n)), reverse=True)
        sources, clusters = [1 << rng.randrange(4) for _ in range(n)], [rng.choice([0, 1, 2]) for _ in range(n)]
        bins, want = [], []
        for s, a, c in zip(sizes, sources, clusters, strict=True):
            fits = [b[0] for b in bins if b[0] >= s and not b[1] & a and not b[2] & c]
            want.append(min(fits, default=None))
            chosen = next((b for b in bins if fits and b[0] == min(fits) and not b[1] & a and not b[2] & c), None)
            if chosen is None:
                chosen = [40, 0, 0]
                bins.append(chosen)
            chosen[0], chosen[1], chosen[2] = chosen[0] - s, chosen[1] | a, chosen[2] | c
        got, rest = packing.best_fit(sizes, sources, clusters, 40), {}
        for s, a, c, k in zip(sizes, sources, clusters, got, strict=True):
            left, mask, held = rest.get(k, (40, 0, 0))
            tightest = min((r for b, (r, m, h) in rest.items() if r >= s and not m & a and not h & c), default=None)
            assert (left == tightest if k in rest else tightest is None) and not mask & a and not held & c and left >= s
            rest[k] = (left - s, mask | a, held | c)
        assert all(r >= 0 for r, _, _ in rest.values())


def test_repeated_takes_any_column_names(spark):
    docs = spark.createDataFrame([(k, "w " * 5, "s", k, 1) for k in range(30)] + [(None, None, None, 3, 2)], "doc_id long, text string, source string, key int, `_copies` int")
    m = mixing.mix(docs.select("doc_id", "text", "source"))
    out = mixing.repeated(docs, m)
    assert out.columns == docs.columns and out.count() == sum(r.copies for r in m.collect())


def test_tiff_contract(spark):
    r = tiff.store_texts(spark.createDataFrame([(1, "héllo"), (2, None)], "doc_id long, text string")).orderBy("doc_id").collect()
    raw = "héllo".encode().ljust(192)
    assert (r[0].n_bytes, r[0].payload_bytes, r[0].payload_sha256, r[0].tail_crc32) == (6, 192, hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-16:]))
    assert (r[1].n_bytes, r[1].payload_bytes) == (0, 192)


def test_packing_rules(spark):
    rng = random.Random(4)
    rows = [(k, " ".join(f"w{rng.randrange(5 if k % 3 == 0 else 999)}" for _ in range(rng.choice([0, 3, 9, 20, 45]))), None if k % 11 == 0 else "hot" if k % 3 else f"s{k % 7}") for k in range(500)]
    out = packing.pack(spark.createDataFrame(rows, "doc_id long, text string, source string"), capacity=20).toPandas()
    live = out[out.bin.notna()]
    assert (live.groupby("bin").n_words.sum() <= 20).all() and not live.assign(s=live.source.fillna("?")).duplicated(["bin", "s"]).any() and not live.duplicated(["bin", "cluster"]).any()
    assert out.groupby("doc_id").n_words.sum().to_dict() == {k: len(t.split()) for k, t, _ in rows}


def test_best_fit_takes_the_tightest_compatible_bin():
    assert packing.best_fit([6, 5, 4, 4], [1, 2, 4, 8], [0, 0, 0, 0], 10) == [0, 1, 0, 1]
    assert packing.best_fit([6, 5, 4, 4], [1, 2, 1, 8], [0, 0, 0, 0], 10) == [0, 1, 1, 0]
    assert packing.best_fit([6, 5, 4], [1, 2, 4], [1, 2, 3], 10) == [0, 1, 2]


def test_warc_long_urls_and_broken_chains(spark, tmp_path):
    rows = [(k, "data:text/plain," + "x" * (200_000 if k == 1 else 9), f"page {k} " * 50) for k in range(4)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)
    assert sorted(r.page_id for r in warc_round_trip(pages).collect()) == [0, 1, 2, 3]
    good = b"WARC/1.1\r\nWARC-Type: response\r\nContent-Length: 2\r\n\r\nab\r\n\r\n"
    (tmp_path / "a.txt").write_bytes(good + good[:-9])
    with pytest.raises(ValueError, match=f"end at {len(good)} of"):
        read_warc(spark, str(tmp_path), payloads=False)


def test_warc_rejects_magic_in_payloads(spark, tmp_path):
    bait = "x\r\n\r\nWARC/1.1\r\nWARC-Type: response\r\nContent-Length: 1\r\n\r\ny\r\n\r\nWARC/1.1\r\n" + "z" * 200
    pages = spark.createDataFrame([(5, "u", bait), (3, "u", bait), (9, "u", "short"), (8, "u", "short"), (1, "u", None)], "page_id long, url string, html string")
    got = {r.page_id: r for r in warc_round_trip(pages).collect()}
    assert len(got) == 5 and all(r.digest_holds for r in got.values())
    assert (got[3].record_type, got[5].record_type, got[5].refers_to) == ("response", "revisit", 3)
    assert got[8].record_type == got[9].record_type == "response"
    assert got[5].payload_digest == hashlib.sha256(bait.encode()).hexdigest() and got[5].payload_bytes == len(bait)
    links = spark.createDataFrame([("f", 0, 10), ("f", 10, 25), ("f", 12, 13), ("f", 13, 99), ("f", 25, 40)], "path string, at long, next long")
    assert sorted(r.at for r in reachable(links).collect()) == [0, 10, 25]


def brute_repeats(texts, width):
    counts = collections.Counter(tuple(w[k : k + width]) for w in texts for k in range(len(w) - width + 1))
    for w in texts:
        gone = [False] * len(w)
        for k in range(len(w) - width + 1):
            if counts[tuple(w[k : k + width])] > 1:
                gone[k : k + width] = [True] * width
        yield [x for x, g in zip(w, gone, strict=True) if not g]


@pytest.mark.parametrize("seed", range(3))
def test_repeats_against_brute_force(spark, seed):
    rng = random.Random(seed)
    common = [f"c{rng.randrange(9)}" for _ in range(60)]
    texts = [[f"w{rng.randrange(40)}" for _ in range(rng.randrange(90))] + common[rng.randrange(30) :] * (k % 3) + ["loop"] * (50 * (k % 4 == 0)) for k in range(60)]
    df = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "doc_id long, text string").repartition(4)
    got = {r.doc_id: r.kept_sha256 for r in remove_repeats(df).select("row.doc_id", "kept_sha256").collect()}
    assert got == {k: hashlib.sha256(" ".join(kept).encode()).hexdigest() for k, kept in enumerate(brute_repeats(texts, 35))}


@pytest.mark.parametrize(("width", "num", "den"), [(4, 85, 100), (5, 80, 100)])
def test_near_duplicates_against_brute_force(spark, width, num, den):
    rng = random.Random(width)
    rows = []
    for family in range(12):
        base = [f"f{family}w{rng.randrange(400)}" for _ in range(rng.choice([3, 12, 60, 250]))]
        for _ in range(12):
            rows.append([w if rng.random() > 0.02 * rng.randrange(3) else f"e{rng.random()}" for w in base])
    docs = list(enumerate(rows)) + [(900, []), (901, [])]
    sets = {i: frozenset([tuple(w)] if 0 < len(w) < width else [tuple(w[k : k + width]) for k in range(len(w) - width + 1)]) for i, w in docs}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and den * len(sets[a] & sets[b]) >= num * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    df = spark.createDataFrame([(i, " ".join(w).upper() if i % 5 == 0 else " ".join(w)) for i, w in docs], "doc_id long, text string")
    # only E, F and W are letters here, so case folding restores every word
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_duplicates(df, Overlap(width, num, den)).collect()}
    assert got == {i: (len(sets[i]), find(i)) for i in sets}
    assert {r.doc_id for r in one_of_each(df, Overlap(width, num, den)).collect()} == {find(i) for i in sets}


def test_components_of_a_long_path(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(40)] + [(100, 101), (5, 5)], "a long, b long")
    got = {r.id: r.component for r in components(edges).collect()}
    assert got == {k: 0 for k in range(41)} | {100: 100, 101: 100}


def test_chat_round_trip_and_role_machine(spark):
    nasty = ["", "\\", "\\b", "### x: </turn>\n", "</turn></turn>\n### assistant: hi", "a\\t\\h", "é😀"]
    rows = [(1, k, "user" if k % 2 == 0 else "assistant", t) for k, t in enumerate(nasty + ["end"])] + [(2, 0, "assistant", "hi"), (3, 0, "role: odd", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    chats = format_chats(df)
    back = {r.conv_id: [(t.role, t.text) for t in r.t] for r in chats.select("conv_id", parse_chats(F.col("formatted")).alias("t")).collect()}
    assert back[1] == [(r, t) for _, _, r, t in rows[:-2]] and back[3] == [("role: odd", "x")]
    d = {r.conv_id: r for r in chat_digest(chats).collect()}
    said = "".join(t for _, _, r, t in rows[:-2] if r == "assistant")
    assert d[1].loss_sha256 == hashlib.sha256(said.encode()).hexdigest() and d[1].valid and not d[2].valid and not d[3].valid


def test_licence_rules_in_order(spark):
    mit = "Intro. " + SENTENCES["mit-grant"] + "\n\n" + SENTENCES["mit-notice"] + " Bye."
    rows = [(1, mit), (2, "Text.\nReleased under  the MIT license.\nLicensed under CC BY-NC 4.0."), (3, SENTENCES["bsd-grant"] + "\n" + SENTENCES["bsd-source"] + "\n" + SENTENCES["bsd-binary"]), (4, "licensed under the Apache")]
    got = {r.doc_id: (r.licenses, r.families) for r in license_scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: ("MIT", "permissive"), 2: ("MIT (line),CC-BY-NC-4.0 (line)", "noncommercial,permissive"), 3: ("BSD-2-Clause", "permissive"), 4: ("", "")}


def test_wrapped_licence_notices(spark):
    import textwrap

    wrapped = lambda ids, mark="": "\n".join(textwrap.wrap(" ".join(SENTENCES[i] for i in ids), 70, initial_indent=mark, subsequent_indent=mark))
    apache = wrapped(["apache-head"], " * ") + "\n * You may obtain a copy of the License at\n *\n *     http://www.apache.org/licenses/LICENSE-2.0\n"
    rows = [(1, wrapped(["mit-grant"], "# ") + "\n\n" + wrapped(["mit-notice"], "# ")), (2, apache), (3, wrapped(["gpl-free", "gpl-hope"])), (4, "Licensed under CC BY. 4.0")]
    got = {r.doc_id: r.licenses for r in license_scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: "MIT", 2: "Apache-2.0", 3: "GPL-3.0-or-later", 4: ""}


def test_given_tables_agree_with_the_licence_sql(spark):
    import duckdb

    docs = duckdb.connect()
    docs.sql(f"create view documents as from '{SF}/documents.parquet'")
    got = queries.op1_license_scan(spark, SF)
    assert sorted(map(tuple, got.collect())) == sorted(docs.sql(f"select {', '.join(got.columns)} from ({queries.ORACLES['op1_license_scan']})").fetchall())


def test_classifier_on_held_out_labels(spark):
    d = SF.replace("0.001", "0.01")
    rated = queries.op6_quality(spark, d).join(table(spark, d, "labels").withColumnRenamed("quality", "y").withColumnRenamed("toxic", "x"), "doc_id").toPandas()
    assert ((rated.quality >= 0.5) == (rated.y == 1)).mean() > 0.97
    clean = rated[(rated.y == 1) & (rated.x == 0)]
    assert clean.keep.mean() > 0.98 and not rated[rated.x == 0].toxic.any()


def test_toxic_scorer_finds_held_out_documents_of_every_language(spark):
    d = SF.replace("0.001", "0.1")
    docs = table(spark, d, "documents").join(table(spark, d, "labels").where("toxic is not null").select("doc_id", "toxic"), "doc_id").withColumn("held", F.pmod(F.xxhash64("text"), F.lit(4)) == 0)
    fitted = docs.where("not held").select("doc_id", "toxic")
    blank = {"weights": np.zeros(quality.BINS + len(quality.SIGNALS) + 1)}
    rated = quality.classify(docs.select("doc_id", "text", "lang", "held", F.col("toxic").alias("y")), fitted, blank).where("row.held").select("row.lang", "row.y", "toxic").toPandas()
    recall = rated[rated.y == 1].groupby("lang").toxic.mean().to_dict()
    assert set(recall) == {"de", "en", "es", "fr"} and min(recall.values()) >= 0.8, recall
    assert rated[rated.y == 0].toxic.mean() < 0.01


def test_pipeline_end_to_end(spark):
    import corpus_pipeline

    out = corpus_pipeline.run(spark, SF).toPandas()
    docs = {r.doc_id for r in table(spark, SF, "documents").collect()}
    assert set(out.doc_id) <= docs and 0 < out.doc_id.nunique() < len(docs)
    live = out[out.bin.notna()]
    assert (live.groupby("bin").n_words.sum() <= packing.CAPACITY).all()
