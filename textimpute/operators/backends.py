"""What answers a prompt: hosted or local language models, scripted answers, and deterministic votes over the evidence.

A model sees prompts only. The evidence backends stay in Spark SQL and stand in for a model where none can be reached; their
figures are not those of a model.
"""

from __future__ import annotations

import json
import math
import time
import urllib.request
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from typing import Protocol

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import shared_folder


class Backend(Protocol):
    def complete(self, prompts: list[str]) -> list[str]: ...


@dataclass
class ScriptedBackend:
    """Answers from a function of the prompt; for tests."""

    answer: Callable[[str], str]

    def complete(self, prompts: list[str]) -> list[str]:
        return [self.answer(p) for p in prompts]


@dataclass
class HttpChatBackend:
    """A hosted chat model behind an HTTP address; retried with growing pauses, at most `per_second` calls a task."""

    url: str
    model: str
    key: str = ""
    per_second: float = 5.0
    retries: int = 4
    timeout: float = 60.0
    headers: dict[str, str] = field(default_factory=dict)

    def _one(self, prompt: str) -> str:
        body = json.dumps({"model": self.model, "messages": [{"role": "user", "content": prompt}], "temperature": 0}).encode()
        head = {"Content-Type": "application/json", **({"Authorization": f"Bearer {self.key}"} if self.key else {}), **self.headers}
        for attempt in range(self.retries + 1):
            try:
                with urllib.request.urlopen(urllib.request.Request(self.url, body, head), timeout=self.timeout) as r:
                    return json.load(r)["choices"][0]["message"]["content"]
            except OSError:
                if attempt == self.retries:
                    raise
                time.sleep(2.0**attempt)
        raise AssertionError

    def complete(self, prompts: list[str]) -> list[str]:
        out = []
        for p in prompts:
            began = time.monotonic()
            out.append(self._one(p))
            time.sleep(max(0.0, 1 / self.per_second - (time.monotonic() - began)))
        return out


@dataclass
class LocalModelBackend:
    """A model in the worker's process: `load` is called once a task and returns a function of a list of prompts."""

    load: Callable[[], Callable[[list[str]], list[str]]]

    def complete(self, prompts: list[str]) -> list[str]:
        if not hasattr(self, "_model"):
            self._model = self.load()
        return self._model(prompts)

    def __getstate__(self):
        return {"load": self.load}


def complete(prompts: DataFrame, backend: Backend, log: str | None = None, batch: int = 32, wave: int = 4096) -> DataFrame:
    """(query_id, prompt_hash, answer). Equal prompts are asked once, in waves of about `wave` prompts.

    A wave's answers are written, by hash, before the next wave is asked: a job that fails loses one wave at most, and a
    rerun with the same log folder asks only what has no answer yet. Without a log the answers go to the shared folder, so
    later actions read them and ask nothing. Within a wave a task that Spark runs again asks its own prompts again.
    """
    spark = prompts.sparkSession
    schema = "prompt_hash string, answer string"
    asked = prompts.select("prompt_hash", "prompt").dropDuplicates(["prompt_hash"])
    if log is None:
        log = shared_folder(spark, "answers")
    elif _exists(spark, log):
        asked = asked.join(spark.read.schema(schema).parquet(log), "prompt_hash", "left_anti")
    queue = shared_folder(spark, "prompts")
    asked.write.parquet(queue)
    waiting = spark.read.schema("prompt_hash string, prompt string").parquet(queue)
    waves = max(1, math.ceil(waiting.count() / wave))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            answers: list[str] = []
            for at in range(0, len(f), batch):
                answers += backend.complete(f["prompt"].iloc[at:at + batch].tolist())
            yield pd.DataFrame({"prompt_hash": f["prompt_hash"], "answer": answers})

    for w in range(waves):
        part = waiting.filter(F.pmod(F.xxhash64("prompt_hash"), F.lit(waves)) == w)
        part.mapInPandas(run, schema).write.mode("append").parquet(log)
    known = spark.read.schema(schema).parquet(log).groupBy("prompt_hash").agg(F.min("answer").alias("answer"))
    return prompts.select("query_id", "prompt_hash").join(known, "prompt_hash")


def _exists(spark: SparkSession, folder: str) -> bool:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path)


def normalise_answer(answer: Column, target: str) -> Column:
    """Trims blanks, a repeated label and quotes."""
    bare = lambda c: F.trim(F.regexp_replace(F.trim(c), "^[\"'`]+|[\"'`.]+$", ""))
    return bare(F.regexp_replace(bare(answer), rf"(?i)^{target}\s*:\s*", ""))


def nearest_vote(examples: DataFrame) -> DataFrame:
    """The target of the most similar example."""
    return examples.filter("rank = 1").select("query_id", F.col("target_value").alias("answer"))


def weighted_vote(examples: DataFrame) -> DataFrame:
    """The target value with the largest sum of similarities (without similarities: of equal weights)."""
    votes = examples.groupBy("query_id", "target_value").agg(F.round(F.sum(F.coalesce("similarity", F.lit(1.0))), 6).alias("weight"), F.min("rank").alias("first"))
    w = Window.partitionBy("query_id").orderBy(F.desc("weight"), "first")
    return votes.withColumn("place", F.row_number().over(w)).filter("place = 1").select("query_id", F.col("target_value").alias("answer"))


def pattern_vote(queries: DataFrame, patterns: DataFrame, examples: DataFrame, row_id: str, attributes: list[str], most: int = 10_000) -> DataFrame:
    """The target whose pattern occurs in the query's cell, the longest deciding; else the nearest example's.

    Patterns come from a sample of bounded size; their number is checked before they are broadcast."""
    n = patterns.count()
    side = patterns.select("attribute", "pattern", F.col("target_value").alias("of_value"))
    side = F.broadcast(side) if n <= most else side
    long = queries.select(F.col(row_id).alias("query_id"), *attributes).unpivot(["query_id"], attributes, "a", "cell")
    hits = long.join(side, (F.col("a") == F.col("attribute")) & F.contains(F.col("cell"), F.col("pattern")))
    w = Window.partitionBy("query_id").orderBy(F.desc(F.length("pattern")), "of_value")
    by_pattern = hits.withColumn("place", F.row_number().over(w)).filter("place = 1").select("query_id", F.col("of_value").alias("found"))
    return (nearest_vote(examples).join(by_pattern, "query_id", "full")
            .select("query_id", F.coalesce("found", "answer").alias("answer")))
