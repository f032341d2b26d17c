"""WARC archives: written by Spark's own text writer, read back with a check of the chain of record boundaries.

A record ends where its length says. Readers cannot trust the magic line alone, since payloads may contain it; so tasks
emit each candidate record with the offset of its successor, and pointer jumping from the start of each file keeps
only records that the chain reaches.

A task cuts a file into ranges. Within a range it follows the successors itself, from each offset at which a record of
another range may end, so one link a range and such offset is left, and pointer jumping joins links of ranges, not of
records.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh_path, join_facts, publish

CRLF = "\r\n"
FILE_BYTES = 64 << 20  # of a file of several records, at most
RANGE_BYTES = 8 << 20  # followed by one task without a join
#: Records of up to so many bytes share files; there is one class of files for each, and one for longer records.
SIZE_CLASSES = (16 << 10, 256 << 10, 4 << 20)
MAGIC = re.compile(rb"WARC/1\.[01]\r\n")


def plan_records(pages: DataFrame, id_col: str = "page_id", body_col: str = "html", url_col: str | None = "url", least: int = 100) -> DataFrame:
    """(page_id, url, payload, payload_bytes, digest, first): first is the smallest id with the payload, null if it is short.

    A null payload is empty. Only digests are grouped; payloads that a large share of the pages have are not shuffled
    to one task.
    """
    body = F.coalesce(F.col(body_col), F.lit(""))
    url = F.col(url_col) if url_col else F.lit(None).cast("string")
    rows = pages.select(F.col(id_col).alias("page_id"), F.regexp_replace(F.coalesce(url, F.lit("")), "[\r\n]+", " ").alias("url"), body.alias("payload"), F.octet_length(body).cast("long").alias("payload_bytes"), F.sha2(body, 256).alias("digest"))
    firsts = rows.where(F.col("payload_bytes") >= least).groupBy("digest").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1 and first is not null")
    return join_facts(rows, publish(firsts, "firsts"), "digest", ["page_id", "url"])


def record_text(date: str) -> Column:
    """The whole record but for its closing CRLF CRLF, which the writer adds."""
    revisit = F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit(CRLF))
    urn = lambda c: F.concat(F.lit("<urn:page:"), c.cast("string"), F.lit(">"))
    head = F.concat(
        F.lit("WARC/1.1" + CRLF),
        line("WARC-Type", F.when(revisit, "revisit").otherwise("response")),
        F.when(F.col("page_id").isNull(), F.lit("")).otherwise(line("WARC-Record-ID", urn(F.col("page_id")))),
        line("WARC-Target-URI", F.col("url")),
        line("WARC-Date", F.lit(date)),
        line("WARC-Payload-Digest", F.concat(F.lit("sha256:"), F.col("digest"))),
        F.when(revisit, F.concat(line("WARC-Profile", F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")), line("WARC-Refers-To", urn(F.col("first"))), line("X-Payload-Length", F.col("payload_bytes").cast("string")))).otherwise(F.lit("")),
        line("Content-Type", F.lit("text/html; charset=utf-8")),
        line("Content-Length", F.when(revisit, F.lit(0)).otherwise(F.col("payload_bytes")).cast("string")),
        F.lit(CRLF),
    )
    return F.concat(head, F.when(revisit, F.lit("")).otherwise(F.col("payload")))


def write_warc(planned: DataFrame, path: str, date: str = "2024-01-01T00:00:00Z", file_bytes: int = FILE_BYTES) -> None:
    """One record a row of plan_records, in files of at most file_bytes or of one record.

    Records are written by classes of size, each with the number of records a file that its largest size allows. Spark's
    committer makes the files of a class appear whole, whatever tasks are retried.
    """
    size = F.octet_length("url") + F.col("payload_bytes") + F.lit(1024)  # the other header lines are shorter
    place = F.lit(len(SIZE_CLASSES))
    for k in reversed(range(len(SIZE_CLASSES))):
        place = F.when(size <= SIZE_CLASSES[k], F.lit(k)).otherwise(place)
    seen = {r["c"] for r in planned.select(place.alias("c")).distinct().collect()}  # four values at most
    for k in sorted(seen) or [0]:
        out = planned.where(place == k).select(record_text(date).alias("value"))
        most = max(1, file_bytes // SIZE_CLASSES[k]) if k < len(SIZE_CLASSES) else 1
        out.write.mode("append").option("lineSep", CRLF * 2).option("maxRecordsPerFile", most).text(path)


def records_of(data: bytes) -> Iterator[tuple]:
    """(at, next, fields, payload start) of each place where a record may begin, in order of its offset."""
    for m in MAGIC.finditer(data):
        at = m.start()
        # A record follows the end of another, so headers searched to their own end never overlap.
        if at and data[at - 4 : at] != b"\r\n\r\n":
            continue
        end = data.find(b"\r\n\r\n", at)
        fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(b":") for x in data[m.end() : end].split(b"\r\n"))} if end >= 0 else {}
        length = fields.get(b"content-length", b"")
        if length.isdigit() and data[end + 4 + int(length) : end + 8 + int(length)] == b"\r\n\r\n":
            yield at, end + 8 + int(length), fields, end + 4


def range_chains(nexts: dict[int, int], width: int) -> tuple[dict[int, int], dict[int, list[int]]]:
    """From candidates at -> next of a file: (exit of each range's entries, entries of the range that lead to a candidate).

    An entry is offset 0 or a candidate that one of an earlier range points at. Its exit is the first offset on its chain
    beyond its range.
    """
    entries = {n for at, n in nexts.items() if n in nexts and n // width != at // width} | ({0} & nexts.keys())
    exits, through = {}, {}
    for entry in sorted(entries):
        at = entry
        while at in nexts and at // width == entry // width:
            through.setdefault(at, []).append(entry)
            at = nexts[at]
        exits[entry] = at
    return exits, through


def candidates(payloads: bool, width: int):
    """(path, content) to rows of two kinds: links of ranges (entry, exit), and candidate records with the entries that lead to them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, content in zip(batch.column("path"), batch.column("content"), strict=True):
                path, data = path.as_py(), content.as_py()
                exits, through = range_chains({at: n for at, n, _, _ in records_of(data)}, width)
                rows = [{"kind": 0, "path": path, "at": a, "next": z, "length": len(data)} for a, z in exits.items()]
                held = 0
                if data and 0 not in exits:
                    rows.append({"kind": 0, "path": path, "at": 0, "next": 0, "length": len(data)})
                for at, n, f, start in records_of(data):
                    if at not in through:
                        continue
                    body, kind = data[start : n - 4], f.get(b"warc-type", b"").decode("utf-8", "replace")
                    number = lambda k, f=f: int(x[1]) if (x := re.fullmatch(rb"<urn:page:(-?\d+)>", f.get(k, b""))) else None
                    stated = f.get(b"warc-payload-digest", b"").decode("ascii", "replace").removeprefix("sha256:")
                    own = kind != "revisit"
                    rows.append({"kind": 1, "path": path, "at": at, "next": n, "entries": through[at], "page_id": number(b"warc-record-id"), "record_type": kind, "refers_to": number(b"warc-refers-to"), "url": f.get(b"warc-target-uri", b"").decode("utf-8", "replace"), "payload_bytes": len(body) if own else int(f.get(b"x-payload-length", b"0") or 0), "payload_digest": hashlib.sha256(body).hexdigest() if own else stated, "stated_digest": stated, "payload": body if own and payloads else None})
                    held += len(body) if payloads else 0
                    if len(rows) >= 4096 or held > FILE_BYTES // 8:
                        yield pa.RecordBatch.from_pylist(rows, SCHEMA)
                        rows, held = [], 0
                yield pa.RecordBatch.from_pylist(rows, SCHEMA)

    return run


SCHEMA = pa.schema([("kind", pa.int32()), ("path", pa.string()), ("at", pa.int64()), ("next", pa.int64()), ("length", pa.int64()), ("entries", pa.list_(pa.int64())), ("page_id", pa.int64()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("stated_digest", pa.string()), ("payload", pa.binary())])
SPARK_SCHEMA = "kind int, path string, at long, next long, length long, entries array<bigint>, page_id long, record_type string, refers_to long, url string, payload_bytes long, payload_digest string, stated_digest string, payload binary"


def reachable(links: DataFrame) -> DataFrame:
    """(path, at) of the records or ranges that a chain from offset 0 of their file reaches, from links (path, at, next).

    Pointers double each round, so a file of n links takes log2(n) rounds of joins on (path, offset).
    """
    jump = publish(links.select("path", "at", "next"), "jump")
    reached = publish(jump.where("at = 0").select("path", "at"), "reached")
    while True:
        ahead = reached.join(jump, ["path", "at"]).select("path", F.col("next").alias("at")).join(links.select("path", "at"), ["path", "at"], "left_semi")
        new = publish(ahead.join(reached, ["path", "at"], "left_anti"), "new")
        if not new.limit(1).count():
            return reached
        reached = publish(reached.union(new), "reached")
        far = jump.select("path", F.col("at").alias("next"), F.col("next").alias("far"))
        jump = publish(jump.join(far, ["path", "next"]).select("path", "at", F.col("far").alias("next")), "jump")


def read_warc(spark: SparkSession, path: str, payloads: bool = True, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """One row per record that its file's chain reaches: path, at, page_id, record_type, refers_to, url, payload_bytes, payload_digest, stated_digest, payload.

    payload is null for revisits, and for all without payloads; the digest and length of revisits come from the header. A
    chain that doesn't end where its file does raises an error; an empty folder gives no rows. A file is read whole by one
    task, so writers bound its bytes (write_warc); Spark refuses files of 2 GB and more.
    """
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.txt").load(path).select("path", "content")
    # Bodies stay out of the published rows; if they are wanted, the archives are read again.
    found = publish(files.mapInArrow(candidates(False, range_bytes), SPARK_SCHEMA), "records")
    links = found.where("kind = 0").select("path", "at", "next", "length")
    keep = publish(reachable(links), "kept")
    ends = links.join(keep, ["path", "at"]).groupBy("path").agg(F.max("next").alias("end"), F.max("length").alias("length"))
    broken = ends.where("end <> length").first()
    if broken:
        raise ValueError(f"{broken['path']}: records end at {broken['end']} of {broken['length']} bytes")
    rows = (files.mapInArrow(candidates(True, range_bytes), SPARK_SCHEMA) if payloads else found).where("kind = 1")
    # Most records have one entry, so this is a join on it; the others are tried with each of theirs.
    one = F.col("path"), F.element_at("entries", 1).alias("entry")
    first = rows.where(F.size("entries") == 1).withColumn("entry", one[1]).join(keep.withColumnRenamed("at", "entry"), ["path", "entry"], "left_semi")
    several = rows.where(F.size("entries") > 1)
    some = found.where("kind = 1").where(F.size("entries") > 1).select("path", "at", F.explode("entries").alias("entry")).join(keep.withColumnRenamed("at", "entry"), ["path", "entry"], "left_semi").select("path", "at").distinct()
    both = first.drop("entry").unionByName(several.join(some, ["path", "at"], "left_semi"))
    return both.select("path", "at", "page_id", "record_type", "refers_to", "url", "payload_bytes", "payload_digest", "stated_digest", "payload")


def warc_round_trip(pages: DataFrame, id_col: str = "page_id", body_col: str = "html", url_col: str | None = "url") -> DataFrame:
    """Write pages as archives in the shared folder and return what reading them back gives, one row per page.

    Rows that repeat an id and payload that is its first are all responses. A null id is read back as null. Null and
    empty pages are responses of no bytes. Other columns are ignored; no rows give no rows.
    """
    spark = pages.sparkSession
    path = fresh_path(spark, "warc")
    write_warc(plan_records(pages, id_col, body_col, url_col), path)
    return read_warc(spark, path, payloads=False).select(F.col("page_id").alias(id_col), "payload_bytes", "payload_digest", "record_type", "refers_to", (F.col("payload_digest") == F.col("stated_digest")).alias("digest_holds"))
