"""Injection of missing values; every choice is a seeded hash of the row id, so engines and reruns agree."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import hash32
from .problem import Task


def _percent(rate: float) -> int:
    return round(rate * 100)


def _masked(df: DataFrame, task: Task, chosen: Column) -> tuple[DataFrame, DataFrame]:
    """(df with chosen targets emptied and is_masked, the truth of the emptied cells)."""
    chosen = chosen & F.col(task.target).isNotNull()
    marked = df.withColumn("is_masked", F.coalesce(chosen, F.lit(False)))
    truth = marked.filter("is_masked").select(task.row_id, F.col(task.target).alias("truth"))
    return marked.withColumn(task.target, F.when(~F.col("is_masked"), F.col(task.target))), truth


def mask_mcar(df: DataFrame, task: Task, rate: float = 0.1, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """Completely at random: every target cell with the same probability."""
    return _masked(df, task, hash32(F.col(task.row_id), str(seed)) % 100 < _percent(rate))


def mask_mar(df: DataFrame, task: Task, on: Column, high: float, low: float, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """At random: the probability depends on a condition over observed columns."""
    return _masked(df, task, hash32(F.col(task.row_id), str(seed)) % 100 < F.when(on, _percent(high)).otherwise(_percent(low)))


def mask_mnar(df: DataFrame, task: Task, on: Column, high: float, low: float, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """Not at random: the probability depends on a condition over the value that goes missing."""
    return mask_mar(df, task, on, high, low, seed)


def mask_by(df: DataFrame, task: Task, by: str, rate: float = 0.1, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """Completely at random over the values of `by`: rows that share one go together, so none gives away another."""
    return _masked(df, task, hash32(F.col(by), str(seed)) % 100 < _percent(rate))


def mask_candidates(df: DataFrame, task: Task, columns: list[str], rate: float, seed: int = 1) -> DataFrame:
    """Empties cells of other attributes, each column by a hash of its own."""
    return df.withColumns({c: F.when(hash32(F.col(task.row_id), str(seed), c) % 100 >= _percent(rate), F.col(c)) for c in columns})
