"""Prompts: a short task text, examples as key-value lines, the incomplete row with an open target; and their cost."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import serialise, words_in
from .problem import Task

TASK_TEXT = "Fill in the missing value of {target}. Answer with the value only."


def serialise_row(attributes: list[str], prefix: str = "") -> Column:
    return serialise({a: F.col(f"{prefix}{a}") for a in attributes})


def build_prompts(queries: DataFrame, pool: DataFrame, examples: DataFrame | None, task: Task, attributes: list[str]) -> DataFrame:
    """(query_id, prompt, k, prompt_hash). examples None: zero-shot.

    Examples are serialised once each and joined by id; an example that very many queries share is one small row.
    """
    attributes = sorted(attributes)
    head = TASK_TEXT.format(target=task.target)
    asked = queries.select(F.col(task.row_id).alias("query_id"), serialise_row(attributes).alias("own"))
    tail = F.concat(F.col("own"), F.when(F.col("own") != "", F.lit("; ")).otherwise(F.lit("")), F.lit(f"{task.target}: "))
    if examples is None:
        out = asked.select("query_id", F.concat(F.lit(head + "\n"), tail).alias("prompt"), F.lit(0).alias("k"))
    else:
        lines = pool.select(F.col(task.row_id).alias("example_id"), serialise_row(attributes).alias("line"))
        used = examples.select("query_id", "rank", "example_id", "target_value")
        shown = F.concat(F.col("line"), F.when(F.col("line") != "", F.lit("; ")).otherwise(F.lit("")), F.lit(f"{task.target}: "), F.col("target_value"))
        per_query = (used.join(lines, "example_id").groupBy("query_id")
                     .agg(F.sort_array(F.collect_list(F.struct("rank", shown.alias("line")))).alias("shots")))
        joined = asked.join(per_query, "query_id", "left")
        shots = F.coalesce(F.transform("shots", lambda s: s["line"]), F.array().cast("array<string>"))
        out = joined.select("query_id", F.array_join(F.concat(F.array(F.lit(head)), shots, F.array(tail)), "\n").alias("prompt"), F.size(shots).alias("k"))
    return out.withColumn("prompt_hash", F.sha2("prompt", 256))


def prompt_tokens(prompts: DataFrame) -> DataFrame:
    """(query_id, k, tokens): blank-separated words of each prompt."""
    return prompts.select("query_id", F.col("k").cast("long").alias("k"), words_in(F.col("prompt")).alias("tokens"))


def prompt_cost(prompts: DataFrame, df: DataFrame, task: Task, attributes: list[str]) -> DataFrame:
    """Measured words a prompt beside the cost formula: words of the task text + k * attributes * mean words a cell."""
    mean = df.select((sum((words_in(F.col(a)) for a in attributes), F.lit(0)) / max(1, len(attributes))).alias("w")).agg(F.avg("w").alias("tau"))
    head = len(TASK_TEXT.format(target=task.target).split())
    measured = prompt_tokens(prompts).agg(F.count("*").alias("prompts"), F.avg("tokens").alias("mean_tokens"), F.sum("tokens").alias("all_tokens"), F.avg("k").alias("mean_k"))
    return measured.crossJoin(mean).select("prompts", "all_tokens", F.round("mean_tokens", 4).alias("mean_tokens"),
                                           F.round(head + F.col("mean_k") * len(attributes) * F.col("tau"), 4).alias("formula_tokens"))


def token_reduction(df: DataFrame, task: Task, attributes: list[str]) -> DataFrame:
    """One minus the words of the selected cells over those of all candidate cells."""
    count = lambda names: sum((words_in(F.col(a)) for a in names), F.lit(0))
    return df.agg(F.sum(count(sorted(attributes))).alias("selected_tokens"), F.sum(count(task.candidates)).alias("all_tokens")).withColumn(
        "reduction", F.round(1 - F.col("selected_tokens") / F.col("all_tokens"), 6))
