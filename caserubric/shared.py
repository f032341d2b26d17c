"""The cluster's shared folder, and tables published there."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one under the warehouse where it is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    return (named or f"{spark.conf.get('spark.sql.warehouse.dir')}/.shared").rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


REMOVE_SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def shuffles_removed(spark: SparkSession) -> Iterator[None]:
    """Queries that run meanwhile remove their shuffle files when they end, not when the driver collects its garbage."""
    before = spark.conf.get(REMOVE_SHUFFLES, None)
    spark.conf.set(REMOVE_SHUFFLES, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(REMOVE_SHUFFLES)
        else:
            spark.conf.set(REMOVE_SHUFFLES, before)


def publish(df: DataFrame, label: str = "table") -> DataFrame:
    """Write df to the shared folder and read it again.

    This cuts the lineage at files that outlive executors, and gives the optimiser true sizes, so that it
    broadcasts a side only when its files are below the session's threshold. The shuffle files of the work are removed at once.
    """
    spark = df.sparkSession
    path = fresh_path(spark, label)
    with shuffles_removed(spark):
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def placed(spark: SparkSession, n: int) -> list[int]:
    """For each of n partitions a number whose hash falls into it, so that repartition(n, number) gives each a partition of its own."""
    from pyspark.sql import functions as F

    if n == 1:
        return [0]
    reach = 32 * n
    while True:
        rows = spark.range(reach).groupBy(F.pmod(F.hash("id"), F.lit(n)).alias("p")).agg(F.min("id").alias("id")).collect()
        if len(rows) == n:
            return [r["id"] for r in sorted(rows, key=lambda r: r["p"])]
        reach *= 2
