"""Streaming surface: filling arriving rows from a frozen pool, monitoring windows, per-target state, deduplication."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.backends import nearest_vote
from ..operators.dependency import Selection
from ..operators.impute import assemble
from ..operators.problem import Task, checked, split
from ..plans.planner import retrieve_planned


def impute_stream(stream: DataFrame, task: Task, selection: Selection, pool: DataFrame, sink: str, checkpoint: str, version: str = "1", trigger: dict | None = None):
    """Fills each micro-batch from the pool and selection of one version and appends it to sink/batch=.../version=....

    The pool is read as a static table; a batch that is run again overwrites its own folder, so results are exactly once.
    """
    known = checked(pool, task).filter(F.col(task.target).isNotNull())

    def fill(batch: DataFrame, number: int) -> None:
        queries, _ = split(checked(batch, task), task)
        answers = nearest_vote(retrieve_planned(queries, known, task, selection.attributes))
        assemble(batch, answers, task).withColumn("version", F.lit(version)).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return stream.writeStream.foreachBatch(fill).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def window_counts(events: DataFrame, ts: str, by: str, width: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Rows and missing values in tumbling (or, with slide, sliding) windows; rows later than the watermark are dropped."""
    timed = events.withWatermark(ts, late) if events.isStreaming else events
    w = F.window(ts, width, slide) if slide else F.window(ts, width)
    return timed.groupBy(w.alias("w"), by).agg(F.count("*").alias("events"), F.sum(F.col("value").isNull().cast("long")).alias("missing")).select(
        F.col("w.start").alias("window_start"), by, "events", "missing")


def session_counts(events: DataFrame, ts: str, key: str, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    timed = events.withWatermark(ts, late) if events.isStreaming else events
    return timed.groupBy(F.session_window(ts, gap).alias("s"), key).agg(F.count("*").alias("events")).select(
        F.col("s.start").alias("session_start"), F.col("s.end").alias("session_end"), key, "events")


def deduplicated(events: DataFrame, ts: str, keys: list[str], late: str = "10 minutes") -> DataFrame:
    if events.isStreaming:
        return events.withWatermark(ts, late).dropDuplicatesWithinWatermark(keys)
    return events.dropDuplicates(keys)


def target_counts(stream: DataFrame, target: str) -> DataFrame:
    """Running number of complete rows of each target value, kept as state: upkeep of the pool's group sizes."""
    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"target_value": [key[0]], "rows": [n]})

    return stream.filter(F.col(target).isNotNull()).select(F.col(target).alias("target_value")).groupBy("target_value").applyInPandasWithState(
        update, "target_value string, rows long", "n long", "update", GroupStateTimeout.NoTimeout)
