from datetime import datetime

from pyspark.sql import functions as F

from caserubric.operators import curation as U
from caserubric.sources.threads import register, upsert
from caserubric.streaming import harvest as H
from caserubric.tables import posts
from conftest import SF


def test_stream_equals_batch_and_redelivery_adds_nothing(spark, tmp_path):
    src, out = str(tmp_path / "in"), str(tmp_path / "out")
    batch = posts(spark, SF)
    batch.repartition(3).write.parquet(src)
    stream = spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", 1).parquet(src)
    keyed = lambda df: df.withColumn("post", F.concat_ws(":", "thread_id", "turn"))
    H.harvest_stream(keyed(stream), out, str(tmp_path / "ck"), "post").awaitTermination()
    found = spark.read.parquet(out)
    assert found.count() == batch.count() and {str(r.harvest_week) for r in found.select("harvest_week").distinct().collect()}
    assert upsert(H.with_week(keyed(batch)), out, "post") == 0


def test_every_message_of_a_thread_is_kept_by_default(spark, tmp_path):
    rows = spark.createDataFrame([(1, 0, "a"), (1, 1, "b"), (1, 1, "b"), (2, 0, "c")], "thread_id long, turn long, text string")
    later = spark.createDataFrame([(1, 1, "b"), (1, 2, "d")], "thread_id long, turn long, text string")
    assert [upsert(x, str(tmp_path / "t")) for x in (rows, rows, later)] == [3, 0, 1]


def test_weekly_counts_of_a_stream(spark, tmp_path):
    src = str(tmp_path / "in")
    batch = posts(spark, SF)
    batch.repartition(2).write.parquet(src)
    stream = spark.readStream.schema(batch.schema).parquet(src)
    q = H.weekly_counts(stream).writeStream.outputMode("complete").format("memory").queryName("weeks").trigger(availableNow=True).start()
    q.awaitTermination()
    want = batch.groupBy(F.date_trunc("week", "posted_at").alias("week"), "platform").agg(F.count(F.lit(1)).alias("posts"))
    assert {tuple(r) for r in spark.table("weeks").collect()} == {tuple(r) for r in want.collect()}


def test_data_source(spark):
    register(spark)
    df = spark.read.format("community_threads").option("threads", 10).option("partitions", 3).load()
    assert df.count() == 20 and df.select("thread_id").distinct().count() == 10


def in_files(spark, folder, schema, *batches):
    """A stream that gets one file of rows after the other."""
    for n, rows in enumerate(batches):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(f"{folder}/{n}")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(folder)


def drained(df, name, path, mode="append"):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", f"{path}/{name}").trigger(availableNow=True).start()
    q.awaitTermination()
    return q


POST = "thread_id long, turn int, role string, text string, posted_at timestamp"


def day(n, hour=0):
    return datetime(2024, 1, n, hour)


def test_threads_close_after_their_pause(spark, tmp_path):
    first = [(1, 1, "assistant", "rest", day(2)), (1, 0, "user", "why?", day(1)), (1, 0, "user", "why?", day(1)), (2, 0, "user", None, day(3))]
    stream = in_files(spark, str(tmp_path / "in"), POST, first, [(3, 0, "user", "later", datetime(2024, 3, 1))], [(4, 0, None, "end", datetime(2024, 3, 2))])
    drained(H.closed_threads(stream, 5), "closed", tmp_path)
    got = {r.thread_id: ([tuple(m) for m in r.messages], r.closed_at) for r in spark.table("closed").collect()}
    assert got == {1: ([(0, "user", "why?"), (1, "assistant", "rest")], day(7)), 2: ([(0, "user", None)], day(8))}
    assert U.screen(spark.table("closed").select("thread_id", "messages")).where("forwarded").count() in (0, 1)


def test_sliding_and_session_windows_equal_batch(spark, tmp_path):
    rows = [(k, 0, "user", "x", day(1 + k, k % 5)) for k in range(20)] + [(1, 1, "user", "y", day(2, 2))]
    schema = POST + ", platform string"
    rows = [(*r, "p") for r in rows]
    batch = spark.createDataFrame(rows, schema)
    slide = lambda df: H.sliding_counts(df).select("window.start", "platform", "posts")
    burst = lambda df: H.bursts(df, "thread_id", gap="2 hours").select("session_window.start", "session_window.end", "thread_id", "posts")
    drained(slide(in_files(spark, str(tmp_path / "a"), schema, rows)), "slides", tmp_path, "complete")
    assert sorted(map(tuple, spark.table("slides").collect())) == sorted(map(tuple, slide(batch).collect()))
    drained(burst(in_files(spark, str(tmp_path / "b"), schema, rows)), "bursts", tmp_path, "complete")
    assert sorted(map(tuple, spark.table("bursts").collect())) == sorted(map(tuple, burst(batch).collect()))


def test_replies_meet_their_questions_in_time(spark, tmp_path):
    asked = in_files(spark, str(tmp_path / "q"), "thread_id long, asked_at timestamp", [(1, day(1)), (2, day(1)), (3, day(2))], [(9, datetime(2024, 5, 1))], [(9, datetime(2024, 5, 2))])
    replied = in_files(spark, str(tmp_path / "r"), "thread_id long, replied_at timestamp", [(1, day(5)), (2, day(25)), (3, day(1))], [(8, datetime(2024, 5, 1))], [(8, datetime(2024, 5, 2))])
    drained(H.answered(asked, replied), "answered", tmp_path)
    got = {r.thread_id: r.replied_at for r in spark.table("answered").where("thread_id < 9").collect()}
    assert got == {1: day(5), 2: None, 3: None}


def test_repeated_texts_and_late_rows(spark, tmp_path):
    a, b, late = (1, 0, "user", "same", day(10)), (2, 0, "user", "same", day(11)), (3, 0, "user", "old", day(1))
    far = (4, 0, "user", "new", datetime(2024, 2, 20))
    stream = in_files(spark, str(tmp_path / "in"), POST, [a, b], [far], [late])
    q = drained(H.distinct_posts(stream), "firsts", tmp_path)
    assert sorted(r.text for r in spark.table("firsts").collect()) == ["new", "same"]
    assert H.late_rows(q) == 1
