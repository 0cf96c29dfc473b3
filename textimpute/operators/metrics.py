"""Accuracy and cost measures."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import unigrams


def judged(answers: DataFrame, truth: DataFrame, row_id: str) -> DataFrame:
    """(query_id, truth, answer): one row per masked cell; the answer is null if none was given."""
    return truth.select(F.col(row_id).alias("query_id"), "truth").join(answers.select("query_id", "answer"), "query_id", "left")


def exact_match(pairs: DataFrame) -> DataFrame:
    """Share of masked cells filled with the truth; `normalised` ignores case and outer blanks."""
    plain = lambda c: F.lower(F.trim(c))
    return pairs.agg(F.count("*").alias("cells"), F.round(F.avg(F.coalesce(F.col("answer") == F.col("truth"), F.lit(False)).cast("double")), 6).alias("exact_match"),
                     F.round(F.avg(F.coalesce(plain(F.col("answer")) == plain(F.col("truth")), F.lit(False)).cast("double")), 6).alias("normalised"))


def rouge1_of(predicted: Column, truth: Column) -> dict[str, Column]:
    """Clipped unigram precision, recall and F1 of one cell."""
    p, t = unigrams(predicted), unigrams(truth)
    both = F.aggregate(F.array_distinct(p), F.lit(0), lambda s, w: s + F.least(F.size(F.filter(p, lambda x: x == w)), F.size(F.filter(t, lambda x: x == w))))
    zero = F.lit(0.0)
    precision = F.when(F.size(p) > 0, both / F.size(p)).otherwise(zero)
    recall = F.when(F.size(t) > 0, both / F.size(t)).otherwise(zero)
    f1 = F.when(both > 0, 2 * both / (F.size(p) + F.size(t))).otherwise(zero)
    return {"precision": precision, "recall": recall, "f1": f1}


def rouge1(pairs: DataFrame) -> DataFrame:
    of = rouge1_of(F.col("answer"), F.col("truth"))
    return pairs.agg(*(F.round(F.avg(c), 6).alias(f"rouge1_{n}") for n, c in of.items()))


def gain(base: Column, new: Column) -> Column:
    """Relative change in percent."""
    return F.round((new / base - 1) * 100, 1)


def mean_std(runs: DataFrame, by: list[str], measure: str) -> DataFrame:
    return runs.groupBy(*by).agg(F.count("*").alias("runs"), F.round(F.avg(measure), 6).alias("mean"), F.round(F.stddev_samp(measure), 6).alias("std"))


def run_seeds(fn: Callable[[int], float], seeds=(1, 2, 3, 4, 5)) -> dict[str, float]:
    values = [fn(s) for s in seeds]
    return {"mean": statistics.fmean(values), "std": statistics.stdev(values) if len(values) > 1 else 0.0}


def retrieval_hit_rate(examples: DataFrame, truth: DataFrame, row_id: str) -> DataFrame:
    """Share of masked cells whose truth is among the example targets."""
    hits = truth.select(F.col(row_id).alias("query_id"), "truth").join(examples.select("query_id", "target_value"), "query_id", "left")
    per = hits.groupBy("query_id").agg(F.max(F.coalesce(F.col("truth") == F.col("target_value"), F.lit(False)).cast("int")).alias("hit"))
    return per.agg(F.count("*").alias("cells"), F.round(F.avg("hit"), 6).alias("hit_rate"))


def seconds(df: DataFrame) -> float:
    """Wall-clock seconds of the whole plan, result thrown away."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def counters(df: DataFrame, pool: DataFrame, attributes: list[str], selected: list[str]) -> DataFrame:
    """The sizes of the cost formulas: rows, complete rows, candidates, selected, mean cell length."""
    mean = sum((F.coalesce(F.length(F.col(a).cast("string")), F.lit(0)) for a in attributes), F.lit(0)) / max(1, len(attributes))
    a = df.agg(F.count("*").alias("rows"), F.round(F.avg(mean), 4).alias("mean_length"))
    return a.crossJoin(pool.agg(F.count("*").alias("complete_rows"))).withColumns({"candidates": F.lit(len(attributes)), "selected": F.lit(len(selected))})
