"""What published tables leave behind, and how often the cascade works."""

import glob

from pyspark.sql import functions as F

from caserubric.operators import curation as U
from caserubric.shared import REMOVE_SHUFFLES, publish


def shuffle_files(spark):
    conf = spark.sparkContext._jsc.sc().env().blockManager().diskBlockManager().localDirsString()
    return {f for top in conf for f in glob.glob(f"{top}/*/shuffle_*.data")}


def test_published_tables_leave_no_shuffle_files(spark):
    before, setting = shuffle_files(spark), spark.conf.get(REMOVE_SHUFFLES)
    wide = spark.range(2000).withColumn("k", F.col("id") % 700).repartition(5, "k").groupBy("k").agg(F.max("id").alias("id"))
    out = publish(wide.repartition(3, "id"))
    assert out.count() == 700 and out.agg(F.sum("id")).first()[0] == wide.agg(F.sum("id")).first()[0]
    publish(wide.repartition(3, "id"))
    kept = spark.conf.get(REMOVE_SHUFFLES)
    assert kept == setting
    held = shuffle_files(spark)
    publish(wide.repartition(4, "id"))
    assert shuffle_files(spark) - held == set() and before is not None


def test_search_and_cascade_run_once(spark):
    """Hits, verdicts and threads are read from files, so no plan on top of them searches or screens again."""
    said = [(1, 0, "user", "My left knee hurts badly. Should I rest the knee today?"), (1, 1, "assistant", "Resting the knee helps badly hurt joints. Call a doctor."), (2, 0, "user", "Hello there")]
    messages = spark.createDataFrame(said, "thread_id long, turn int, role string, text string")
    docs = spark.createDataFrame([(1, "resting the knee helps hurt joints badly", 0), (2, "call a doctor", 0)], "doc_id long, text string, toxic int")
    done = U.curate(messages, docs)
    for df in (done.cases, done.rejects, done.funnel, done.threads):
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert "MapInArrow" not in plan and "regexp_extract(" not in plan
    assert [r["remaining"] for r in done.funnel.orderBy("step").collect()][0] == 2
    assert {r["thread_id"] for r in done.cases.select(F.col("case_id").alias("thread_id")).union(done.rejects.select("thread_id")).collect()} == {1, 2}
