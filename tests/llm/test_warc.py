"""WARC: ranges against a plain walk along the chain, size classes, nested archives."""

import hashlib
import random

import pytest

from caserubric.llm.warc import plan_records, range_chains, read_warc, records_of, warc_round_trip, write_warc


def record(body: bytes, number: int) -> bytes:
    return b"WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:page:%d>\r\nContent-Length: %d\r\n\r\n" % (number, len(body)) + body + b"\r\n\r\n"


def walk(data: bytes) -> list[int]:
    nexts, at, out = {a: n for a, n, _, _ in records_of(data)}, 0, []
    while at in nexts:
        out.append(at)
        at = nexts[at]
    return out


@pytest.mark.parametrize("seed", [0])
def test_ranges_give_what_the_chain_gives(spark, tmp_path, seed):
    """Payloads hold whole records, heads without ends and archives of their own."""
    rng, files, number = random.Random(seed), {}, 0
    for name in "ab":
        data = b""
        for _ in range(40):
            inner = [b"x" * rng.randrange(90), record(b"fake", 999), b"\r\n\r\nWARC/1.1\r\nContent-Length: 7\r\n\r\n", b"\r\n\r\n" + record(b"y" * rng.randrange(300), 998) * 3]
            data += record(b"".join(rng.choices(inner, k=rng.randrange(4))), number)
            number += 1
        files[name] = data
        (tmp_path / f"{name}.txt").write_bytes(data)
    (tmp_path / "empty.txt").write_bytes(b"")
    want = sorted(range(number))
    for width in (900, 1 << 20):
        for payloads in (False, True):
            got = read_warc(spark, str(tmp_path), payloads, width).collect()
            assert sorted(r.page_id for r in got) == want
            assert not payloads or all(hashlib.sha256(bytes(r.payload)).hexdigest() == r.payload_digest for r in got)
    for data in files.values():
        exits, through = range_chains({a: n for a, n, _, _ in records_of(data)}, 300)
        assert set(walk(data)) <= set(through) and exits


def test_long_pages_have_files_of_their_own(spark, tmp_path):
    rows = [(k, "u", "p" * n + str(k)) for k, n in enumerate([10, 200, 20_000, 300_000, 300_000, 5_000_000, 0])] + [(7, "u" * 70_000, "z" * 500), (8, None, None), (9, "u", "p" * 5_000_000 + "5")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(2)
    write_warc(plan_records(pages), str(tmp_path / "w"), file_bytes=1 << 20)
    sizes = [f.stat().st_size for f in (tmp_path / "w").glob("*.txt")]
    assert sum(s > 1 << 20 for s in sizes) == 1 and len(sizes) >= 4
    got = {r.page_id: r for r in warc_round_trip(pages).collect()}
    assert sorted(got) == list(range(10)) and all(r.digest_holds for r in got.values())
    for i, _, html in rows:
        body = (html or "").encode()
        assert (got[i].payload_bytes, got[i].payload_digest) == (len(body), hashlib.sha256(body).hexdigest())
    assert (got[9].record_type, got[9].refers_to, got[5].record_type) == ("revisit", 5, "response")
    with pytest.raises(ValueError, match="records end at 0 of"):
        (tmp_path / "w" / "z.txt").write_bytes(b"no archive")
        read_warc(spark, str(tmp_path / "w"))
