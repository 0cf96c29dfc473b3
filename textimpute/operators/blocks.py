"""Retrieval on one attribute without comparing pairs: queries walk automata of the pool, not its rows.

A block is a share of the complete rows of one target value. Of each block and cell length one suffix automaton is built,
whose states know the smallest row id that holds their substrings. A query's walk through it gives the longest substring
shared with any of these rows, and so the best similarity there, in time proportional to the query's length: work is
queries * blocks * lengths instead of queries * rows. Blocks hold at most BLOCK_CHARS characters, so a target value with
very many rows is several blocks.
"""

from __future__ import annotations

import math
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.automaton import SuffixAutomaton
from .problem import Task
from .retrieval import _for_queries, _ranked, collapse_pool, collapse_queries

#: Characters of one block (an automaton takes a few hundred bytes a character).
BLOCK_CHARS = 100_000
#: Characters of the queries that are broadcast at a time.
SLICE_CHARS = 16_000_000


class Block:
    """The rows of one target value: the best similarity of any of them to a cell, and the smallest row id that has it."""

    def __init__(self, cells: list[str | None], ids: list[Any]):
        self.first = min(ids)
        by_length: dict[int, dict[str, Any]] = {}
        for cell, i in zip(cells, ids):
            if cell:
                rows = by_length.setdefault(len(cell), {})
                rows[cell] = min(i, rows.get(cell, i))
        self.parts = []
        for length in sorted(by_length):
            rows = sorted(by_length[length].items(), key=lambda x: (x[1], x[0]))
            automaton = SuffixAutomaton(*(c for c, _ in rows))
            holder: list[Any] = [None] * len(automaton.next)
            for cell, i in rows:  # smallest id first: a state that has one, and all shorter suffixes, keep it
                state = 0
                for c in cell:
                    state = up = automaton.next[state][c]
                    while up > 0 and holder[up] is None:
                        holder[up] = i
                        up = automaton.link[up]
            self.parts.append((length, automaton, holder))
        self.walks = 0

    def best(self, cell: str | None) -> tuple[float, Any]:
        if not cell:
            return 0.0, self.first
        size, best, found = len(cell), 0.0, self.first
        for length, automaton, holder in sorted(self.parts, key=lambda p: abs(p[0] - size)):
            if round(min(length, size) / max(length, size), 9) < best:
                continue  # no row of this length can be as similar
            self.walks += 1
            state = n = longest = 0
            holders: list[Any] = []
            for c in cell:
                while state and c not in automaton.next[state]:
                    state = automaton.link[state]
                    n = automaton.length[state]
                if c in automaton.next[state]:
                    state, n = automaton.next[state][c], n + 1
                    if n > longest:
                        longest, holders = n, [holder[state]]
                    elif n == longest:
                        holders.append(holder[state])
            similarity = round(longest / max(length, size), 9)
            if longest and (similarity > best or similarity == best and min(holders) < found):
                best, found = similarity, min(holders)
        return best, found


def retrieve_blocks(queries: DataFrame, pool: DataFrame, task: Task, attribute: str, k: int | None = None, block_chars: int = BLOCK_CHARS,
                    slice_chars: int = SLICE_CHARS) -> DataFrame:
    """The same result as retrieve(..., [attribute], diverse=True).

    Distinct queries are broadcast in slices of at most slice_chars characters, so the driver holds one slice at a time.
    """
    k = k or task.k
    left, right = collapse_queries(queries, [attribute]), collapse_pool(pool, task, [attribute])
    chars = F.coalesce(F.length("p0"), F.lit(0)) + 1
    sizes = right.groupBy(F.col("target_value").alias("t")).agg(F.ceil(F.sum(chars) / block_chars).cast("int").alias("blocks"))
    many = sizes.filter("blocks > 1")  # one row for each block_chars characters at most
    dealt = (right.join(F.broadcast(many), F.col("target_value") == F.col("t"), "left")
             .withColumn("block", F.pmod(F.xxhash64("example_id"), F.coalesce("blocks", F.lit(1))).cast("int")).select("target_value", "block", "p0", "example_id"))
    asked = left.agg(F.sum(F.coalesce(F.length("q0"), F.lit(0)) + 65)).first()[0] or 0
    slices = max(1, math.ceil(asked / slice_chars))
    kind = dict(right.dtypes)["example_id"]
    schema = f"cells_id string, target_value string, example_id {kind}, similarity double"
    found = None
    for s in range(slices):
        part = left if slices == 1 else left.filter(F.pmod(F.xxhash64("cells_id"), F.lit(slices)) == s)
        shared = left.sparkSession.sparkContext.broadcast([(r["cells_id"], r["q0"]) for r in part.select("cells_id", "q0").toLocalIterator()])
        here = dealt.groupBy("target_value", "block").applyInPandas(_compare(shared), schema)
        found = here if found is None else found.unionByName(here)
    return _for_queries(_ranked(found, k, True), queries, task, [attribute])


def _compare(shared):
    """The best row of a block for each of the broadcast queries."""
    def run(key: tuple[Any, ...], rows: pd.DataFrame) -> pd.DataFrame:
        block = Block([c if isinstance(c, str) else None for c in rows["p0"]], rows["example_id"].tolist())
        best = [block.best(cell) for _, cell in shared.value]
        return pd.DataFrame({"cells_id": [c for c, _ in shared.value], "target_value": key[0], "example_id": [i for _, i in best], "similarity": [x for x, _ in best]})

    return run


def work(queries: DataFrame, pool: DataFrame, task: Task, attribute: str) -> DataFrame:
    """One row: distinct queries and pool rows, the pairs a nested comparison would score, and the walks through automata
    that replace them at most."""
    left, right = collapse_queries(queries, [attribute]), collapse_pool(pool, task, [attribute])
    a = left.agg(F.count("*").alias("queries"))
    b = right.agg(F.count("*").alias("pool_rows"), F.countDistinct("target_value", F.coalesce(F.length("p0"), F.lit(0))).alias("automata"))
    return a.crossJoin(b).select("queries", "pool_rows", (F.col("queries") * F.col("pool_rows")).alias("pairs"), (F.col("queries") * F.col("automata")).alias("walks"))

