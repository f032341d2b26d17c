"""Agents that answer prompts in batches, with a cache. Rules stand in for the four language models of the method."""

from __future__ import annotations

import json
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Agent:
    """answer maps a batch of prompts to as many answers; it is where a model endpoint would plug in."""

    name: str
    params_b: int
    answer: Callable[[pd.Series], pd.Series]


def claim_prompt(claim: Column, ground: Column) -> Column:
    """The prompt of the agents that judge a claim against a ground."""
    return F.to_json(F.struct(claim.alias("claim"), ground.alias("ground")))


def content_words(text: str | None) -> set[str]:
    return {w for w in re.findall(r"[^\W_]+", (text or "").lower()) if len(w) >= 4}


def covers(tau: float) -> Callable[[pd.Series], pd.Series]:
    """1 if the ground holds the share tau of the claim's content words, else 0; a claim without any isn't covered."""

    def one(prompt: str) -> str:
        asked = json.loads(prompt)
        need = content_words(asked.get("claim"))
        return str(int(bool(need) and len(need & content_words(asked.get("ground"))) / len(need) >= tau))

    return lambda prompts: prompts.map(one)


SCREENER = Agent("screener", 4, lambda prompts: prompts.str.contains("[?？]").astype(int).astype(str))
VALIDATOR = Agent("validator", 120, covers(0.4))
CONTROLLER = Agent("controller", 4, covers(1.0))
GRADER = Agent("grader", 120, covers(0.8))

ANSWERS = "agent string, hash string, answer string"


def kept_answers(like: DataFrame, agent: Agent, cache: str) -> DataFrame:
    """(hash, answer) of the agent's prompts in the cache."""
    spark = like.sparkSession
    try:
        kept = spark.read.schema(ANSWERS).parquet(cache)
    except AnalysisException as fault:  # no cache yet
        if fault.getCondition() != "PATH_NOT_FOUND":
            raise
        kept = spark.createDataFrame([], ANSWERS)
    return kept.where(F.col("agent") == agent.name).select("hash", "answer").dropDuplicates(["hash"])


def ask(requests: DataFrame, agent: Agent, cache: str, prompt: str = "prompt") -> DataFrame:
    """requests with answer. Equal prompts are asked once, and none that the cache, a Parquet folder, holds.

    The new answers are written before any is used, so a task that is run again later calls no agent. Null prompts are
    asked as empty ones. An answer column of requests is replaced.
    """
    named = requests.drop("answer").withColumn("_prompt", F.coalesce(prompt, F.lit(""))).withColumn("_hash", F.sha2("_prompt", 256))
    missing = named.select(F.col("_hash").alias("hash"), F.col("_prompt").alias("prompt")).dropDuplicates(["hash"]).join(kept_answers(requests, agent, cache), "hash", "left_anti")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            yield pd.DataFrame({"agent": agent.name, "hash": frame["hash"], "answer": agent.answer(frame["prompt"])})

    missing.mapInPandas(run, ANSWERS).write.mode("append").parquet(cache)
    found = kept_answers(requests, agent, cache).withColumnRenamed("hash", "_hash")
    return named.join(found, "_hash").drop("_hash", "_prompt")
