"""Pattern mining: substrings frequent in the rows of one target value and in no other's.

All work is on the sample in long form (attribute, target_value, row_id, value), at most m * n rows an attribute.
"""

from __future__ import annotations

from itertools import count
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.automaton import SuffixAutomaton
from ..functions.lcstable import LcsTable
from .problem import Task

PATTERN_SCHEMA = "attribute string, target_value string, pattern string, support long, group_rows long"
MODES = ("maximal", "longest", "all", "pairwise")


def unpivot_sample(sample: DataFrame, task: Task) -> DataFrame:
    """(attribute, target_value, row_id, value); an empty cell stays as a null value and counts as a row."""
    renamed = sample.select(F.col(task.row_id).cast("string").alias("row_id"), F.col(task.target).alias("target_value"), *(c for c in task.candidates))
    return renamed.unpivot(["row_id", "target_value"], list(task.candidates), "attribute", "value")


def pairwise_common(texts: list[str]) -> set[str]:
    """The longest common substring of each text with each one before it (the place that comes first in the later text)."""
    first, last = {}, {}
    for i, t in enumerate(texts):
        first.setdefault(t, i)
        last[t] = i
    table, starts, common = LcsTable(list(first)), np.array(list(first.values())), set()
    for t, i in last.items():
        n, end = table.longest(t)
        before = (starts < i) & (n > 0)
        for e, k in zip(*divmod(np.unique(end[before].astype("int64") * (len(t) + 1) + n[before]), len(t) + 1)):
            common.add(t[e - k:e])
    return common


def mine_group(values: list, q: float, mode: str = "maximal", min_len: int = 1, max_len: int | None = None, min_support_rows: int = 1,
               max_patterns: int | None = None) -> list[tuple[str, int]]:
    """The patterns of one group's cells (in the order of their row ids) and their support; empty cells count as rows."""
    texts = [v for v in values if isinstance(v, str) and v]
    least = max(q * len(values), min_support_rows, 1e-9)
    if not texts:
        found = []
    elif mode == "all":
        found = SuffixAutomaton(*texts).frequent(least)
    elif mode == "pairwise":
        found = SuffixAutomaton(*texts).supported(pairwise_common(texts), least)
    else:
        found = SuffixAutomaton(*texts).maximal(least)
        if mode == "longest" and found:
            longest = max(len(c) for c, _ in found)
            found = [x for x in found if len(x[0]) == longest]
    return [(c, n) for c, n in found if len(c) >= min_len and (max_len is None or len(c) <= max_len)][:max_patterns]


def mine_frequent(long: DataFrame, q: float, mode: str = "maximal", min_len: int = 1, max_len: int | None = None,
                  min_support_rows: int = 1, max_patterns: int | None = None) -> DataFrame:
    """Substrings in at least a share q of a group's rows.

    mode `maximal`: those that no other such substring extends (complete for the dependency test); `longest`: only the
    longest of them; `all`: every one; `pairwise`: longest common substrings of pairs of rows that are frequent (may miss
    a shorter unique one). q = 1 gives the substrings common to all rows. max_len and max_patterns may lose patterns; both
    are off by default. What `longest`, `pairwise` or a limit leave out may still be frequent in another group, so
    uniqueness has to be decided in the rows then (unique_in_rows).
    """
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")

    def mine(key: tuple[Any, ...], rows: pd.DataFrame) -> pd.DataFrame:
        found = mine_group(rows.sort_values("row_id")["value"].tolist(), q, mode, min_len, max_len, min_support_rows, max_patterns)
        n = len(found)
        text = lambda values: pd.Series(values, dtype=object)
        return pd.DataFrame({"attribute": text([key[0]] * n), "target_value": text([key[1]] * n), "pattern": text([c for c, _ in found]),
                             "support": pd.Series([s for _, s in found], dtype="int64"), "group_rows": pd.Series([len(rows)] * n, dtype="int64")})

    if mode == "pairwise":  # few bytes, much work: groups by size would go to one task
        long = long.repartition(2 * long.sparkSession.sparkContext.defaultParallelism, "attribute", "target_value")
    return long.groupBy("attribute", "target_value").applyInPandas(mine, PATTERN_SCHEMA)


def mine_frequent_native(long: DataFrame, q: float, max_len: int | None = None) -> DataFrame:
    """All frequent substrings level by level without Python: a longer one is counted only where both its parts that are
    one character shorter were frequent (support cannot grow with length). Ends with the first length that has none, or
    with max_len."""
    keys = ["attribute", "target_value"]
    sizes = long.groupBy(*keys).agg(F.count("*").alias("group_rows"))
    rows = long.filter(F.length("value") > 0).cache()
    levels, frequent = [], None
    for n in count(1) if max_len is None else range(1, max_len + 1):
        grams = F.array_distinct(F.transform(F.sequence(F.lit(1), F.length("value") - n + 1), lambda i: F.substring("value", i, n)))
        here = rows.filter(F.length("value") >= n).select(*keys, "row_id", F.explode(grams).alias("pattern")).dropDuplicates([*keys, "row_id", "pattern"])
        if frequent is not None:
            for part in (F.substring("pattern", 1, n - 1), F.expr(f"substring(pattern, 2, {n - 1})")):
                here = here.withColumn("part", part).join(frequent.select(*keys, F.col("pattern").alias("part")), [*keys, "part"], "left_semi").drop("part")
        counted = here.groupBy(*keys, "pattern").agg(F.count("*").alias("support"))
        frequent = counted.join(F.broadcast(sizes), keys).filter(F.col("support") >= q * F.col("group_rows")).select(*keys, "pattern", "support", "group_rows").cache()
        if frequent.isEmpty():
            break
        levels.append(frequent)
    out = levels[0] if levels else frequent
    for level in levels[1:]:
        out = out.unionByName(level)
    return out


def unique_in_rows(frequent: DataFrame, long: DataFrame, q: float) -> DataFrame:
    """Drops a pattern that is frequent in another group as well, counted in the rows: right for every mode and limit."""
    wanted = frequent.select(F.col("attribute").alias("a"), "pattern").distinct()
    hits = long.join(wanted, (F.col("attribute") == F.col("a")) & F.contains(F.col("value"), F.col("pattern"))).groupBy("attribute", "pattern", "target_value").agg(F.count("*").alias("n"))
    sizes = long.groupBy(F.col("attribute").alias("a"), F.col("target_value").alias("t")).agg(F.count("*").alias("rows"))
    often = hits.join(sizes, (F.col("attribute") == F.col("a")) & (F.col("target_value") == F.col("t"))).filter(F.col("n") >= q * F.col("rows"))
    alone = often.groupBy("attribute", "pattern").agg(F.count("*").alias("groups")).filter("groups = 1")
    return frequent.join(alone, ["attribute", "pattern"], "left_semi").select(frequent.columns)


def unique_for(frequent: DataFrame, long: DataFrame, q: float, mode: str) -> DataFrame:
    """Unique patterns the cheaper way that is right for the mode (mined without limits)."""
    return unique_patterns(frequent) if mode in ("maximal", "all") else unique_in_rows(frequent, long, q)


def unique_patterns(frequent: DataFrame) -> DataFrame:
    """Drops a pattern that is frequent in another group as well; for `maximal` and `all` patterns mined without limits.

    A substring is frequent in a group exactly if a maximal frequent one of that group contains it, so the patterns alone
    decide and the rows need not be read again.
    """
    other = frequent.select(F.col("attribute").alias("a"), F.col("target_value").alias("t"), F.col("pattern").alias("o"))
    same = (F.col("attribute") == F.col("a")) & (F.col("target_value") != F.col("t")) & F.contains(F.col("o"), F.col("pattern"))
    return frequent.join(other, same, "left_anti")


def drop_contained(patterns: DataFrame) -> DataFrame:
    """Drops a pattern that a longer one of the same group contains; for readers only, the test does not change."""
    other = patterns.select(F.col("attribute").alias("a"), F.col("target_value").alias("t"), F.col("pattern").alias("o"))
    inside = ((F.col("attribute") == F.col("a")) & (F.col("target_value") == F.col("t")) & (F.length("o") > F.length("pattern"))
              & F.contains(F.col("o"), F.col("pattern")))
    return patterns.join(other, inside, "left_anti")


def recheck_full(pool: DataFrame, patterns: DataFrame, task: Task, most: int = 10_000) -> DataFrame:
    """Support of each kept pattern in every group of the whole table, in one scan.

    A sample cannot show that a pattern is unique among groups that were not drawn. The patterns are broadcast, so their
    number is checked first.
    """
    kept = patterns.select("attribute", "target_value", "pattern").distinct()
    n = kept.count()
    if n > most:
        raise ValueError(f"{n} patterns are too many to broadcast; keep the longest ones")
    long = unpivot_sample(pool, task)
    side = F.broadcast(kept.select(F.col("attribute").alias("a"), F.col("target_value").alias("of_value"), "pattern"))
    hits = long.join(side, (F.col("attribute") == F.col("a")) & F.contains(F.col("value"), F.col("pattern")))
    counts = hits.groupBy("attribute", "of_value", "pattern", "target_value").agg(F.count("*").alias("support"))
    sizes = pool.groupBy(F.col(task.target).alias("g")).agg(F.count("*").alias("group_rows"))
    return (counts.join(sizes, F.col("target_value") == F.col("g")).drop("g")
            .withColumn("frequent", F.col("support") >= task.q * F.col("group_rows")))
