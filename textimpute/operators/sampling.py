"""Samples for pattern mining: whole groups of rows with one target value, or single rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import hash32
from .problem import Task


def group_sizes(pool: DataFrame, task: Task) -> DataFrame:
    return pool.filter(F.col(task.target).isNotNull()).groupBy(task.target).agg(F.count("*").alias("group_rows"))


def shortfall_quota(sizes: dict[int, int], m: int, n: int) -> dict[int, int]:
    """How many groups to draw of each size (sizes above n count as n), largest first, within m * n rows."""
    budget, quota = m * n, {}
    for size in sorted((s for s in sizes if s > 0), reverse=True):
        take = min(sizes[size], budget // size)
        if take:
            quota[size] = take
            budget -= take * size
    return quota


def sample_groups(pool: DataFrame, task: Task) -> DataFrame:
    """m groups of n rows each; if there are not enough groups of n rows, smaller whole groups fill the row budget.

    The driver sees one number for each size up to n, and the at most m * n chosen values. Groups and rows are ranked by
    seeded hashes; the rank limits are applied before each shuffle, so a very large group moves n rows per task at most.
    """
    seed = str(task.seed)
    sizes = group_sizes(pool, task).withColumn("size", F.least(F.col("group_rows"), F.lit(task.n)).cast("int")).persist()  # one row a target value, read twice
    histogram = {r["size"]: r["groups"] for r in sizes.groupBy("size").agg(F.count("*").alias("groups")).collect()}
    quota = shortfall_quota(histogram, task.m, task.n)
    if not quota:
        sizes.unpersist()
        return pool.limit(0)
    of_size = F.create_map(*[F.lit(x) for kv in quota.items() for x in kv])
    by_group = Window.partitionBy("size").orderBy(hash32(F.col(task.target), seed), F.col(task.target))
    chosen = (sizes.filter(F.col("size").isin(*quota)).withColumn("place", F.row_number().over(by_group)).filter(F.col("place") <= task.m * task.n)
              .filter(F.col("place") <= of_size[F.col("size")]).select(task.target).collect())
    sizes.unpersist()
    by_row = Window.partitionBy(task.target).orderBy(hash32(F.col(task.row_id), seed), F.col(task.row_id))
    return (pool.filter(F.col(task.target).isin([r[0] for r in chosen]))
            .withColumn("__place", F.row_number().over(by_row)).filter(F.col("__place") <= task.n).drop("__place"))


def sample_uniform(pool: DataFrame, task: Task, rows: int) -> DataFrame:
    """The contrast: rows drawn alike, so frequent target values crowd out rare ones."""
    h = hash32(F.col(task.row_id), str(task.seed))
    return pool.filter(F.col(task.target).isNotNull()).orderBy(h, task.row_id).limit(rows)


def draw(pool: DataFrame, task: Task) -> DataFrame:
    return pool if task.m is None or task.n is None else sample_groups(pool, task)


def coverage(sample: DataFrame, pool: DataFrame, task: Task) -> DataFrame:
    """Distinct target values in the sample and in the table."""
    a = sample.agg(F.count("*").alias("sample_rows"), F.countDistinct(task.target).alias("sample_values"))
    b = pool.agg(F.countDistinct(task.target).alias("table_values"))
    return a.crossJoin(b).withColumn("covered", F.round(F.col("sample_values") / F.col("table_values"), 6))
