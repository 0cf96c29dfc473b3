"""From a table with empty cells to a filled one with the evidence behind every filled cell."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.lcs import lcs_str
from ..plans.planner import retrieve_planned
from .backends import Backend, complete, nearest_vote, normalise_answer, pattern_vote, weighted_vote
from .dependency import Selection, select_attributes
from .problem import Task, checked, split
from .prompting import build_prompts
from .retrieval import retrieve_fixed, retrieve_random

VOTES = ("nearest_vote", "weighted_vote", "pattern_vote")


@dataclass
class Imputed:
    table: DataFrame  # the input columns, missing targets filled, and target_imputed
    answers: DataFrame  # query_id, answer
    examples: DataFrame | None
    selection: Selection
    prompts: DataFrame | None = None


def assemble(df: DataFrame, answers: DataFrame, task: Task) -> DataFrame:
    """Fills empty target cells only; every other cell stays as it is. Rows that share a row id get the same answer."""
    flag = f"{task.target}_imputed"
    found = answers.groupBy(F.col("query_id").alias("__q")).agg(F.min("answer").alias("__a"))
    joined = df.join(found, df[task.row_id] == F.col("__q"), "left")
    empty = F.col(task.target).isNull()
    columns = [F.when(empty, F.col("__a").cast(df.schema[task.target].dataType)).otherwise(F.col(c)).alias(c) if c == task.target else F.col(c) for c in df.columns]
    return joined.select(*columns, (empty & F.col("__a").isNotNull()).alias(flag))


def impute(df: DataFrame, task: Task, backend: Backend | str = "pattern_vote", selection: Selection | None = None, examples: str | list = "diverse",
           attributes: list[str] | None = None, log: str | None = None) -> Imputed:
    """The localized imputer, its ablations and its zero-shot form.

    examples: `diverse`, `plain` (similar, targets may repeat), `random`, `random_run`, `none` (zero-shot) or row ids.
    attributes: overrides the selection (all candidates: the all-attributes arms). backend: a model or a vote's name.
    """
    text = checked(df, task)
    queries, pool = split(text, task)
    if selection is None:
        selection = Selection(sorted(attributes)) if attributes is not None else select_attributes(text, task)
    names = sorted(attributes) if attributes is not None else selection.attributes
    if examples in ("diverse", "plain"):
        found = retrieve_planned(queries, pool, task, names, diverse=examples == "diverse")
    elif examples in ("random", "random_run"):
        found = retrieve_random(queries, pool, task, per="query" if examples == "random" else "run")
    elif examples == "none":
        found = None
    else:
        found = retrieve_fixed(queries, pool, task, list(examples))
    prompts = None
    if isinstance(backend, str):
        if backend not in VOTES or found is None:
            raise ValueError(f"votes are {VOTES} and need examples")
        if backend == "pattern_vote" and selection.patterns is not None:
            answers = pattern_vote(queries, selection.patterns, found, task.row_id, names)
        else:
            answers = (weighted_vote if backend == "weighted_vote" else nearest_vote)(found)
    else:
        prompts = build_prompts(queries, pool, found, task, names)
        answers = complete(prompts, backend, log).select("query_id", normalise_answer(F.col("answer"), task.target).alias("answer"))
    return Imputed(assemble(df, answers, task), answers, found, selection, prompts)


def impute_many(df: DataFrame, tasks: list[Task], **options) -> DataFrame:
    """One task per column, each from the table as it was given."""
    out = df
    for task in tasks:
        out = assemble(out, impute(df, task, **options).answers, task)
    return out


def explain(df: DataFrame, task: Task, result: Imputed) -> DataFrame:
    """One row per filled cell, example and selected attribute: rank, similarity and the common substring that counted."""
    text = checked(df, task)
    names = result.selection.attributes
    long = lambda key, cell: text.select(F.col(task.row_id).alias(key), *names).unpivot([key], names, "attribute", cell)
    used = result.examples.join(long("query_id", "query_cell"), "query_id")
    joined = used.join(long("example_id", "example_cell"), ["example_id", "attribute"]).join(result.answers, "query_id", "left")
    return joined.select("query_id", "answer", "rank", "example_id", "target_value", "similarity", "attribute",
                         lcs_str(F.coalesce("query_cell", F.lit("")), F.coalesce("example_cell", F.lit(""))).alias("common"))
