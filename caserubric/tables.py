"""Loaders, and the views that give the tables their roles: star track for scoring, text track for curation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

MODELS = 38
THEMES = 5
#: Models that rise after their cutoff in the simulated grader, by number modulo 6.
RISING = 5


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def star_cases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """case_id, theme, specialty, source, lang, published: one order each."""
    customer = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    nation = load(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", "o_orderdate")
    joined = orders.join(customer, orders.o_custkey == customer.c_custkey).join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.select(F.col("o_orderkey").alias("case_id"), F.col("o_orderpriority").alias("theme"), F.col("n_name").alias("specialty"), (F.col("o_custkey") % 4).cast("int").alias("source"), (F.col("n_regionkey") % 2).cast("int").alias("lang"), F.to_date("o_orderdate").alias("published"))


def star_criteria(spark: SparkSession, sf_dir: str) -> DataFrame:
    """case_id, criterion_no, weight, axis, status, published: one line item each, numbered by all its columns."""
    item = load(spark, sf_dir, "lineitem")
    part = load(spark, sf_dir, "part").select("p_partkey", "p_brand")
    number = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*item.columns))
    size = (F.lit(1) + F.col("l_quantity").cast("int") % 10).cast("int")
    rows = item.join(part, item.l_partkey == part.p_partkey).withColumn("criterion_no", number)
    return rows.select(F.col("l_orderkey").alias("case_id"), F.col("criterion_no").cast("int"), F.when(F.col("l_returnflag") == "R", -size).otherwise(size).alias("weight"), (F.substring("p_brand", 7, 9).cast("int") % 5).alias("axis"))


def model_columns(m: Column) -> dict[str, Column]:
    day = F.date_add(F.lit("1996-01-01").cast("date"), (m * 40).cast("int"))
    unknown = m % 7 == 3
    return {
        "model_id": m.cast("int"),
        "access": F.when(m % 2 == 0, "proprietary").otherwise("open"),
        "domain": F.when(m % 5 == 0, "medical").otherwise("general"),
        "params_b": (F.lit(4) + (m * 13) % 120).cast("int"),
        "cutoff": F.when(~unknown, day),
        "released": F.date_add(day, 120),
    }


def models(spark: SparkSession) -> DataFrame:
    """The registry: model_id, access, domain, params_b, cutoff (null for some), released."""
    cols = model_columns(F.col("id"))
    return spark.range(MODELS).select(*[c.alias(k) for k, c in cols.items()])


def simulated_met(case: Column, criterion: Column, model: Column, newer: Column) -> Column:
    """The stand-in for a grader: integers only, so that other engines agree bit for bit."""
    luck = F.pmod(case.cast("long") * 7919 + criterion.cast("long") * 104729 + model.cast("long") * 1299709, F.lit(1000003)) % 100
    drift = F.when(~newer, 0).when(model % 6 == RISING, 2).otherwise(-5)
    return luck < F.lit(20) + model + drift


def star_judged(spark: SparkSession, sf_dir: str) -> DataFrame:
    """model_id, case_id, criterion_no, weight, axis, met, published: every criterion judged for every model.

    The models are an exploded sequence, so the matrix is made within the task that holds a case and is never shuffled.
    """
    dates = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("case_id"), F.to_date("o_orderdate").alias("published"))
    rows = star_criteria(spark, sf_dir).join(dates, "case_id")
    wide = rows.withColumn("model_id", F.explode(F.sequence(F.lit(0), F.lit(MODELS - 1))))
    m = model_columns(F.col("model_id"))
    newer = F.col("published") > F.coalesce(m["cutoff"], m["released"])
    return wide.withColumn("met", simulated_met(F.col("case_id"), F.col("criterion_no"), F.col("model_id"), newer))


def posts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """thread_id, turn, role, text, posted_at, platform: conversation rows dated by an event each."""
    events = load(spark, sf_dir, "events").select("event_id", "ts")
    n = F.lit(events.count())
    rows = load(spark, sf_dir, "conversations").withColumn("event_id", (F.col("conv_id") * 97) % n)
    return rows.join(events, "event_id").select(F.col("conv_id").alias("thread_id"), "turn", "role", "text", F.col("ts").cast("timestamp").alias("posted_at"), F.concat(F.lit("p"), F.col("conv_id") % 4).alias("platform"))


TAGS = ("cardiology", "oncology", "career", "exam", "paediatrics", "surgery", "neurology")


def threads_to_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """thread_id, text, posted_at, tags, replied: what the post filters look at, one row a conversation.

    The tables have no tags and no attachments: a thread's tag hangs on its number, and every eleventh thread shows a
    picture. Its text is that of all turns but notices.
    """
    rows = posts(spark, sf_dir).where("role <> 'system'")
    text = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))), lambda m: m["text"]), "\n")
    out = rows.groupBy("thread_id").agg(text.alias("text"), F.min("posted_at").alias("posted_at"), F.bool_or(F.col("role") == "assistant").alias("replied"))
    tag = F.element_at(F.array(*map(F.lit, TAGS)), (F.col("thread_id") % len(TAGS) + 1).cast("int"))
    return out.select("thread_id", F.when(F.col("thread_id") % 11 == 0, F.concat("text", F.lit("\n[image]"))).otherwise(F.col("text")).alias("text"), "posted_at", F.array(tag).alias("tags"), "replied")
