"""The task: one target attribute, candidate attributes, a row id; the complete and the incomplete rows."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import as_text


@dataclass(frozen=True)
class Task:
    """target: the attribute to fill; row_id: a unique key; candidates: the attributes that may explain the target.

    p, q: share of target values that need a pattern, share of a value's rows that a pattern has to occur in.
    m, n: groups and rows a group of the sample (None: no sampling). k: examples for each missing value.
    """

    target: str
    row_id: str
    candidates: tuple[str, ...]
    p: float = 0.75
    q: float = 0.75
    m: int | None = 10
    n: int | None = 10
    k: int = 10
    seed: int = 1

    def __post_init__(self):
        if self.target in self.candidates or self.target == self.row_id:
            raise ValueError("the target cannot explain or identify itself")

    def but(self, **changes) -> Task:
        return replace(self, **changes)


def checked(df: DataFrame, task: Task) -> DataFrame:
    """The task's columns as text (the row id as it is); raises if one is missing."""
    missing = {task.target, task.row_id, *task.candidates} - set(df.columns)
    if missing:
        raise ValueError(f"no such column: {', '.join(sorted(missing))}")
    return df.select(task.row_id, *(as_text(df, c).alias(c) for c in (task.target, *task.candidates) if c != task.row_id))


def split(df: DataFrame, task: Task) -> tuple[DataFrame, DataFrame]:
    """(rows with an empty target, rows with a known one)."""
    return df.filter(F.col(task.target).isNull()), df.filter(F.col(task.target).isNotNull())


def diagnose(df: DataFrame, task: Task) -> DataFrame:
    """One row on the assumptions: do target values repeat, how many are missing, are candidates observed."""
    per_value = df.filter(F.col(task.target).isNotNull()).groupBy(task.target).agg(F.count("*").alias("n"))
    values = per_value.agg(F.count("*").alias("distinct_values"), F.coalesce(F.sum("n"), F.lit(0)).alias("complete_rows"),
                           F.round(F.avg((F.col("n") >= 2).cast("double")), 6).alias("repeated_share"))
    nulls = [F.round(F.avg(F.col(c).isNull().cast("double")), 6).alias(f"null_{c}") for c in task.candidates]
    rows = df.agg(F.count("*").alias("all_rows"), F.coalesce(F.sum(F.col(task.target).isNull().cast("long")), F.lit(0)).alias("missing_rows"), *nulls)
    return rows.crossJoin(values)  # one row each
