"""Chooses how examples are retrieved from sizes that are cheap to count, and says why."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.blocks import retrieve_blocks
from ..operators.problem import Task
from ..operators.retrieval import PAIR_BUDGET, PAIR_LIMIT, retrieve, retrieve_indexed


#: Pairs up to which a nested loop is quicker than building automata.
FEW_PAIRS = 20_000


@dataclass(frozen=True)
class RetrievalPlan:
    way: str  # `nested`, `blocks` or `indexed`
    longest: int
    g: int
    reason: str
    cost: float = 0.0  # pairs times characters


def choose_retrieval(queries: DataFrame, pool: DataFrame, attributes: list[str], budget: float = PAIR_BUDGET) -> RetrievalPlan:
    """One attribute: automata of the pool's blocks, unless there are few pairs. Several: a nested loop while queries * pool
    * characters stay in the budget; else the gram index, with grams long enough that random pairs seldom share one (a third
    of the mean cell, between 3 and 12)."""
    sizes = [F.count("*").alias("n")]
    for i, a in enumerate(sorted(attributes)):
        sizes += [F.coalesce(F.max(F.length(a)), F.lit(0)).alias(f"x{i}"), F.coalesce(F.avg(F.length(a)), F.lit(0.0)).alias(f"m{i}")]
    a, b = queries.agg(*sizes).first(), pool.agg(*sizes).first()
    n = len(attributes)
    longest = max([0, *(r[f"x{i}"] for r in (a, b) for i in range(n))])
    mean = sum(b[f"m{i}"] for i in range(n))
    cost = a["n"] * b["n"] * max(1.0, mean)
    g = max(3, min(12, int(mean / max(1, n) / 3)))
    if n == 1 and a["n"] * b["n"] > FEW_PAIRS:
        return RetrievalPlan("blocks", longest, g, f"one attribute and {a['n'] * b['n']:.3g} pairs", cost)
    if cost <= budget:
        return RetrievalPlan("nested", longest, g, f"{cost:.3g} character pairs are within {budget:.3g}", cost)
    return RetrievalPlan("indexed", longest, g, f"{cost:.3g} character pairs exceed {budget:.3g}", cost)


def retrieve_planned(queries: DataFrame, pool: DataFrame, task: Task, attributes: list[str], diverse: bool = True) -> DataFrame:
    plan = choose_retrieval(queries, pool, attributes)
    if plan.way == "blocks" and diverse:
        return retrieve_blocks(queries, pool, task, attributes[0])
    if plan.way == "indexed" and diverse:
        return retrieve_indexed(queries, pool, task, attributes, g=plan.g, longest=plan.longest)
    if plan.cost > PAIR_LIMIT:
        raise ValueError(f"a nested comparison would cost {plan.cost:.3g} character pairs, more than {PAIR_LIMIT:.3g}")
    return retrieve(queries, pool, task, attributes, diverse=diverse, longest=plan.longest)
