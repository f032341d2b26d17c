"""The weekly harvest as a stream."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..sources.threads import upsert, with_week


def timed(posts: DataFrame, ts: str = "posted_at", delay: str = "7 days") -> DataFrame:
    """posts with a watermark; watermarks need a timestamp with zone, so the column is cast."""
    return posts.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def weekly_counts(posts: DataFrame, ts: str = "posted_at") -> DataFrame:
    """week, platform, posts in tumbling weeks that start on Monday."""
    return timed(posts, ts).groupBy(F.window(ts, "7 days", startTime="4 days"), "platform").agg(F.count(F.lit(1)).alias("posts")).select(F.col("window.start").alias("week"), "platform", "posts")


def sliding_counts(posts: DataFrame, ts: str = "posted_at") -> DataFrame:
    return timed(posts, ts).groupBy(F.window(ts, "28 days", "7 days"), "platform").agg(F.count(F.lit(1)).alias("posts"))


def bursts(posts: DataFrame, who: str, ts: str = "posted_at", gap: str = "1 hour") -> DataFrame:
    """Sessions of one author with no longer pause than the gap."""
    return timed(posts, ts).groupBy(F.session_window(ts, gap), who).agg(F.count(F.lit(1)).alias("posts"))


def answered(questions: DataFrame, replies: DataFrame, days: int = 14) -> DataFrame:
    """Questions (thread_id, asked_at) with a reply (thread_id, replied_at) within the time, or null once that is past."""
    q = timed(questions, "asked_at").alias("q")
    r = timed(replies, "replied_at").alias("r")
    near = (F.col("q.thread_id") == F.col("r.thread_id")) & (F.col("replied_at") >= F.col("asked_at")) & (F.col("replied_at") <= F.col("asked_at") + F.expr(f"INTERVAL {days} DAYS"))
    return q.join(r, near, "leftOuter").select("q.thread_id", "asked_at", "replied_at")


def distinct_posts(posts: DataFrame, ts: str = "posted_at") -> DataFrame:
    """The first post of each text within the watermark; state ends with it."""
    return timed(posts, ts).withColumn("content_key", F.xxhash64(F.lower("text"))).dropDuplicatesWithinWatermark(["content_key"])


MESSAGES = "array<struct<turn: long, role: string, text: string>>"


def closed_threads(posts: DataFrame, days: int = 14, ts: str = "posted_at", delay: str = "7 days") -> DataFrame:
    """thread_id, messages in turn order, closed_at of each thread, once no message of it came for so many days of event time.

    The columns are those that the screening takes. The state of a thread is its messages, which go when it closes; a
    message that is delivered twice counts once, and one that comes after the thread closed opens it anew. Messages
    without a thread or a time are left out; null texts and roles are kept.
    """
    span = days * 86_400_000

    def close(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            buffer, last = state.get
            state.remove()
            rows = sorted({(t, r, x) for t, r, x in json.loads(buffer)}, key=lambda m: (m[0], m[1] or "", m[2] or ""))
            said = json.dumps([{"turn": t, "role": r, "text": x} for t, r, x in rows])
            yield pd.DataFrame({"thread_id": [key[0]], "said": [said], "closed_at": [last + span]})
            return
        buffer, last = state.get if state.exists else ("[]", 0)
        held = json.loads(buffer)
        for frame in frames:
            held += [[t, r, x] for t, r, x in zip(frame["turn"].tolist(), frame["role"].tolist(), frame["text"].tolist(), strict=True)]
            last = max(last, int(frame["at"].max()))
        state.update((json.dumps(held), last))
        state.setTimeoutTimestamp(max(last + span, state.getCurrentWatermarkMs() + 1))

    rows = timed(posts.where(F.col("thread_id").isNotNull() & F.col(ts).isNotNull()), ts, delay).select("thread_id", F.coalesce(F.col("turn"), F.lit(0)).cast("long").alias("turn"), "role", "text", ts, F.unix_millis(ts).alias("at"))
    out = rows.groupBy("thread_id").applyInPandasWithState(close, "thread_id long, said string, closed_at long", "buffer string, last long", "append", "EventTimeTimeout")
    return out.select("thread_id", F.from_json("said", MESSAGES).alias("messages"), F.timestamp_millis("closed_at").alias("closed_at"))


def late_rows(query: StreamingQuery) -> int:
    """Rows that came behind the watermark and were dropped, over the progress that the query keeps."""
    return sum(s.numRowsDroppedByWatermark for p in query.recentProgress for s in p.stateOperators)


def harvest_stream(posts: DataFrame, out: str, checkpoint: str, key: str | tuple[str, ...] = ("thread_id", "turn")) -> StreamingQuery:
    """Append what the index lacks, batch by batch. A batch that is delivered again after a failure adds nothing."""

    def write(batch: DataFrame, number: int) -> None:
        upsert(with_week(batch), out, key)

    return posts.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
