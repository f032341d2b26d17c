"""A Python data source for community threads, and sinks for harvested weeks."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "thread_id long, turn long, role string, text string"


class ThreadPartition(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class ThreadReader(DataSourceReader):
    """Made-up threads first..last, dealt evenly over the partitions; each is made where it is read."""

    def __init__(self, options: dict):
        self.threads, self.parts = int(options.get("threads", 100)), int(options.get("partitions", 4))

    def partitions(self) -> list[ThreadPartition]:
        cuts = [self.threads * k // self.parts for k in range(self.parts + 1)]
        return [ThreadPartition(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition: ThreadPartition) -> Iterator[tuple]:
        for k in range(partition.first, partition.last):
            yield (k, 0, "user", f"I have had complaint number {k} for {k % 9 + 1} days. What helps?")
            yield (k, 1, "assistant", f"Remedy number {k % 17} helps. Come back if it lasts.")


class CommunityThreads(DataSource):
    @classmethod
    def name(cls) -> str:
        return "community_threads"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> ThreadReader:
        return ThreadReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CommunityThreads)


def append_week(posts: DataFrame, path: str) -> None:
    """Append a harvest, laid out by harvest_week for pruning."""
    posts.write.mode("append").partitionBy("harvest_week").parquet(path)


def upsert(batch: DataFrame, path: str, key: str | tuple[str, ...] = ("thread_id", "turn")) -> int:
    """Append the rows whose key the table lacks; delivering a batch twice changes nothing. Returns the rows added.

    A row is a message unless another key is given, so later replies of a known thread are added.
    """
    spark, keys = batch.sparkSession, [key] if isinstance(key, str) else list(key)
    fresh = batch.dropDuplicates(keys)
    try:
        fresh = fresh.join(spark.read.parquet(path).select(*keys), keys, "left_anti")
    except AnalysisException as fault:  # no table yet
        if fault.getCondition() not in ("PATH_NOT_FOUND", "UNABLE_TO_INFER_SCHEMA"):
            raise
    fresh = fresh.persist()
    n = fresh.count()
    if n:
        fresh.write.mode("append").parquet(path)
    fresh.unpersist()
    return n


def with_week(posts: DataFrame, ts: str = "posted_at") -> DataFrame:
    return posts.withColumn("harvest_week", F.date_trunc("week", F.col(ts)).cast("date"))
