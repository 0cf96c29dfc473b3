"""Approximate dependencies by patterns, the selection of attributes, and strict dependencies for contrast."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .patterns import PATTERN_SCHEMA, drop_contained, mine_frequent, mine_group, unique_for, unpivot_sample
from .problem import Task
from .sampling import draw


def evaluate(patterns: DataFrame, long: DataFrame, p: float) -> DataFrame:
    """(attribute, covered, groups, fraction, holds): the share of target values that have a pattern of their own."""
    groups = long.groupBy("attribute").agg(F.countDistinct("target_value").alias("groups"))
    covered = patterns.groupBy("attribute").agg(F.countDistinct("target_value").alias("covered"))
    share = F.col("covered") / F.col("groups")
    return (groups.join(covered, "attribute", "left").withColumn("covered", F.coalesce("covered", F.lit(0).cast("long")))
            .select("attribute", "covered", "groups", F.round(share, 6).alias("fraction"), (share >= p).alias("holds")))


#: Characters of a sample up to which it is mined on the driver: a sample has at most m * n rows.
LOCAL_CHARS = 200_000


def measure(pool: DataFrame, task: Task, mode: str = "maximal", local_chars: int = LOCAL_CHARS) -> tuple[DataFrame, DataFrame]:
    """(evidence, unique patterns) of the task's sample of complete rows.

    A bounded sample (m and n given) whose cells are short is fetched and mined on the driver, which saves several tiny
    jobs: at most m * n rows of cells of local_chars / (m * n) characters. Otherwise each group is mined in a task.
    """
    return measure_each(pool, [task], mode, local_chars)[0]


def measure_each(pool: DataFrame, tasks: list[Task], mode: str = "maximal", local_chars: int = LOCAL_CHARS) -> list[tuple[DataFrame, DataFrame]]:
    """measure() of tasks that differ in p and q only, on one sample."""
    task = tasks[0]
    if any(t.but(p=task.p, q=task.q) != task for t in tasks):
        raise ValueError("tasks may differ in p and q only")
    sample = draw(pool, task)
    if task.m is not None and task.n is not None:
        cut = local_chars // (task.m * task.n)
        rows = sample.select(task.row_id, task.target, *(F.substring(c, 1, cut + 1).alias(c) for c in task.candidates)).collect()  # at most m * n
        if all(r[c] is None or len(r[c]) <= cut for r in rows for c in task.candidates):
            return [_measured_locally(pool.sparkSession, rows, t, mode) for t in tasks]
    long = unpivot_sample(sample, task)
    found = [unique_for(mine_frequent(long, t.q, mode), long, t.q, mode) for t in tasks]
    return [(evaluate(patterns, long, t.p), patterns) for t, patterns in zip(tasks, found)]


def _measured_locally(spark, rows: list, task: Task, mode: str) -> tuple[DataFrame, DataFrame]:
    evidence, unique = [], []
    for a in task.candidates:
        groups: dict[str, list] = {}
        for r in sorted(rows, key=lambda r: str(r[task.row_id])):
            groups.setdefault(r[task.target], []).append(r[a])
        mined = {g: mine_group(v, task.q, mode) for g, v in groups.items()}
        covered = 0
        for g, found in mined.items():
            others = [(o, v) for o, v in groups.items() if o != g]
            alone = [(p, n) for p, n in found if not any(_frequent(p, v, mined[o], task.q, mode) for o, v in others)]
            covered += bool(alone)
            unique += [(a, g, p, n, len(groups[g])) for p, n in alone]
        if groups:
            share = covered / len(groups)
            evidence.append((a, covered, len(groups), round(share, 6), share >= task.p))
    return (spark.createDataFrame(evidence, "attribute string, covered long, groups long, fraction double, holds boolean"), spark.createDataFrame(unique, PATTERN_SCHEMA))


def _frequent(pattern: str, values: list, mined: list[tuple[str, int]], q: float, mode: str) -> bool:
    """Whether the pattern is frequent in a group: a maximal pattern of it says so, or its cells do."""
    if mode in ("maximal", "all"):
        return any(pattern in o for o, _ in mined)
    n = sum(isinstance(v, str) and pattern in v for v in values)
    return n > 0 and n >= q * len(values)


@dataclass
class Selection:
    """attributes: the names that phase 2 uses; evidence: one row per candidate; patterns: what justifies the choice."""

    attributes: list[str]
    evidence: DataFrame | None = None
    patterns: DataFrame | None = None
    note: str = ""


def select_attributes(df: DataFrame, task: Task, mode: str = "maximal", readable: bool = True, on_empty: str = "all") -> Selection:
    """Sample groups, mine patterns, keep those of one group only, keep attributes that cover a share p of the groups.

    p = 0 or q = 0 ask for nothing: all candidates stay. on_empty says what to do if none holds: `all`, `best` (the
    highest share) or `error`.
    """
    if not task.p or not task.q:
        return Selection(sorted(task.candidates), note="no constraint")
    evidence, patterns = measure(df.filter(F.col(task.target).isNotNull()), task, mode)
    if readable:
        patterns = drop_contained(patterns)
    rows = evidence.collect()  # one row a candidate
    kept = sorted(r["attribute"] for r in rows if r["holds"])
    if kept or not rows:
        return Selection(kept or sorted(task.candidates), evidence, patterns)
    if on_empty == "error":
        raise ValueError("no attribute depends on the target at these p and q")
    if on_empty == "best":
        top = max(rows, key=lambda r: (r["fraction"], r["attribute"]))
        return Selection([top["attribute"]], evidence, patterns, "none held; the best was kept")
    return Selection(sorted(task.candidates), evidence, patterns, "none held; all were kept")


def fd_holds(df: DataFrame, attribute: str, target: str) -> DataFrame:
    """Does every value of the attribute occur with one target value only, in this table?"""
    per_value = df.filter(F.col(attribute).isNotNull() & F.col(target).isNotNull()).groupBy(attribute).agg(F.countDistinct(target).alias("n"))
    return per_value.agg(F.count("*").alias("values"), F.coalesce(F.sum((F.col("n") > 1).cast("long")), F.lit(0)).alias("violating_values"),
                         (F.coalesce(F.max("n"), F.lit(1)) <= 1).alias("holds"))


def fd_violation_rate(df: DataFrame, attribute: str, target: str) -> DataFrame:
    """Share of rows that would have to go for the strict dependency to hold."""
    pairs = df.filter(F.col(attribute).isNotNull() & F.col(target).isNotNull()).groupBy(attribute, target).agg(F.count("*").alias("n"))
    best = pairs.groupBy(attribute).agg(F.sum("n").alias("rows"), F.max("n").alias("kept"))
    return best.agg(F.sum("rows").alias("rows"), F.round(1 - F.sum("kept") / F.sum("rows"), 6).alias("violation_rate"))


def top_value(counts: DataFrame, by: list[str], value: str, n: str = "n") -> DataFrame:
    """The most frequent value of each key (ties: the smaller value)."""
    w = Window.partitionBy(*by).orderBy(F.desc(n), F.col(value))
    return counts.withColumn("__place", F.row_number().over(w)).filter("__place = 1").drop("__place")
