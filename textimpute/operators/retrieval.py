"""Example retrieval: for each incomplete row the most similar complete rows with pairwise different target values.

All functions take queries and pool with the columns of a Task and return
(query_id, rank, example_id, target_value, similarity), rank from 1.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.automaton import SuffixAutomaton
from ..functions.lcs import cell_similarity, lcs_len_arrow
from ..functions.text import hash32
from ..functions.windows import WindowSet, window_hashes
from .compare import candidates, vector_candidates
from .problem import Task

#: Pairs times characters that a nested-loop comparison may cost before the planner asks for the index.
PAIR_BUDGET = 1e8
#: Characters of long cells whose automata a task keeps.
AUTOMATA_CHARS = 200_000
#: Pairs beyond which a nested loop is refused.
PAIR_LIMIT = 1e11


def guarded(queries: int, rows: int, limit: float = PAIR_LIMIT) -> None:
    if queries * rows > limit:
        raise ValueError(f"{queries} queries against {rows} rows are {queries * rows:.3g} pairs, more than {limit:.3g}")


def thinned_pool(pool: DataFrame, task: Task, most: int) -> DataFrame:
    """Approximate mode: at most `most` complete rows of each target value, by hash. To be reported with recall()."""
    w = Window.partitionBy(task.target).orderBy(hash32(F.col(task.row_id), str(task.seed)), task.row_id)
    return pool.filter(F.col(task.target).isNotNull()).withColumn("__place", F.row_number().over(w)).filter(F.col("__place") <= most).drop("__place")


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """One row: exact examples, those found with the same similarity or a higher one at the same rank, and their share."""
    both = exact.select("query_id", "rank", F.col("similarity").alias("of_exact")).join(found.select("query_id", "rank", "similarity"), ["query_id", "rank"], "left")
    hit = F.coalesce(F.col("similarity") >= F.col("of_exact"), F.lit(False)).cast("long")
    return both.agg(F.count("*").alias("examples"), F.coalesce(F.sum(hit), F.lit(0)).alias("found"), F.round(F.avg(hit), 6).alias("recall"))


def collapse_pool(pool: DataFrame, task: Task, attributes: list[str]) -> DataFrame:
    """One row for each combination of selected cells and target: (p0.., target_value, example_id = smallest row id)."""
    cells = [F.col(a).alias(f"p{i}") for i, a in enumerate(attributes)]
    kept = pool.filter(F.col(task.target).isNotNull()).select(*cells, F.col(task.target).alias("target_value"), F.col(task.row_id).alias("example_id"))
    return kept.groupBy(*(f"p{i}" for i in range(len(attributes))), "target_value").agg(F.min("example_id").alias("example_id"))


def collapse_queries(queries: DataFrame, attributes: list[str]) -> DataFrame:
    """Distinct selected cells of the queries: (q0.., cells_id)."""
    cells = [F.col(a).alias(f"q{i}") for i, a in enumerate(attributes)]
    names = [f"q{i}" for i in range(len(attributes))]
    return queries.select(*cells).distinct().withColumn("cells_id", cells_key(names))


def cells_key(names: list[str]) -> Column:
    """A key of the cells that tells nulls from texts."""
    return F.sha2(F.to_json(F.array(*names)), 256) if names else F.lit("")


def similarity(attributes: list[str], longest: int | None) -> Column:
    """Mean over the attributes (in sorted order) of LCS length over the longer length; a null cell counts 0."""
    if not attributes:
        return F.lit(0.0)
    total = F.lit(0.0)
    for i in range(len(attributes)):
        total = total + cell_similarity(F.col(f"q{i}"), F.col(f"p{i}"), longest)
    return F.round(total / len(attributes), 9)


def upper_bound(attributes: list[str]) -> Column:
    """No pair can be more similar than the mean of shorter over longer length."""
    total = F.lit(0.0)
    for i in range(len(attributes)):
        a, b = F.length(f"q{i}"), F.length(f"p{i}")
        total = total + F.coalesce(F.when(F.greatest(a, b) > 0, F.least(a, b) / F.greatest(a, b)), F.lit(0.0))
    return F.round(total / max(1, len(attributes)), 9)


def longest_cell(df: DataFrame, attributes: list[str]) -> int:
    if not attributes:
        return 0
    row = df.agg(*[F.max(F.length(a)).alias(a) for a in attributes]).first()
    return max([0, *(x for x in row if x is not None)])


def _ranked(scored: DataFrame, k: int, diverse: bool, backfill: bool = False) -> DataFrame:
    """The k best examples of each cells_id; with `diverse` only the best of each target value. Ties: smaller row id.
    backfill: where there are fewer than k target values, the best of the other rows follow.

    Both limits are applied before their shuffles (window group limits)."""
    best_first = [F.desc("similarity"), F.col("example_id")]
    if diverse and backfill:
        per_value = Window.partitionBy("cells_id", "target_value").orderBy(*best_first)
        # of one value at most k rows can be wanted
        scored = scored.withColumn("__v", F.row_number().over(per_value)).filter(F.col("__v") <= k)
        per_query = Window.partitionBy("cells_id").orderBy(F.col("__v") > 1, *best_first)
        return scored.withColumn("rank", F.row_number().over(per_query)).filter(F.col("rank") <= k).drop("__v")
    if diverse:
        per_value = Window.partitionBy("cells_id", "target_value").orderBy(*best_first)
        scored = scored.withColumn("__v", F.row_number().over(per_value)).filter("__v = 1").drop("__v")
    per_query = Window.partitionBy("cells_id").orderBy(*best_first)
    return scored.withColumn("rank", F.row_number().over(per_query)).filter(F.col("rank") <= k)


def _for_queries(ranked: DataFrame, queries: DataFrame, task: Task, attributes: list[str]) -> DataFrame:
    keyed = queries.select(F.col(task.row_id).alias("query_id"), *(F.col(a).alias(f"q{i}") for i, a in enumerate(attributes)))
    keyed = keyed.select("query_id", cells_key([f"q{i}" for i in range(len(attributes))]).alias("cells_id"))
    return keyed.join(ranked, "cells_id").select("query_id", "rank", "example_id", "target_value", "similarity")


def retrieve(queries: DataFrame, pool: DataFrame, task: Task, attributes: list[str], k: int | None = None, diverse: bool = True, longest: int | None = None,
             backfill: bool = False) -> DataFrame:
    """Compares every distinct query with every distinct pool row, block by block (see compare); `longest` is not needed.
    backfill: see _ranked; every complete row then counts, also equal ones."""
    k, attributes = k or task.k, sorted(attributes)
    left, right = collapse_queries(queries, attributes), collapse_pool(pool, task, attributes) if diverse and not backfill else plain_pool(pool, task, attributes)
    scored = candidates(left, spread(right), len(attributes), k, diverse, backfill)
    return _for_queries(_ranked(scored, k, diverse, backfill), queries, task, attributes)


def spread(rows: DataFrame) -> DataFrame:
    """Rows over all cores: their bytes are few, so a shuffle by size would leave the comparisons to a task or two."""
    return rows.repartition(2 * rows.sparkSession.sparkContext.defaultParallelism)


def plain_pool(pool: DataFrame, task: Task, attributes: list[str]) -> DataFrame:
    """Every complete row, not collapsed."""
    return pool.filter(F.col(task.target).isNotNull()).select(
        *(F.col(a).alias(f"p{i}") for i, a in enumerate(attributes)), F.col(task.target).alias("target_value"), F.col(task.row_id).alias("example_id"))


def grams(cell: Column, g: int) -> Column:
    return F.when(F.length(cell) >= g, F.array_distinct(F.transform(F.sequence(F.lit(1), F.length(cell) - g + 1), lambda i: F.substring(cell, i, g)))).otherwise(F.array().cast("array<string>"))


def retrieve_indexed(queries: DataFrame, pool: DataFrame, task: Task, attributes: list[str], k: int | None = None, g: int = 3,
                     longest: int | None = None, max_posting: int | None = None, report: bool = False) -> DataFrame:
    """The same result as retrieve() from pairs that share a g-gram in some attribute, certified query by query. Each block
    of the pool has its own posting lists, so pairs are not shuffled.

    A pair without a common g-gram has LCS lengths below g, so its similarity is at most the mean of (g - 1) / query cell
    length. If a query's k-th example lies above that, the pairs that were not compared cannot matter; the other queries,
    and only they, are compared with the whole pool. max_posting drops grams with longer posting lists (approximate; then
    nothing is certified and recall is to be reported). report: adds `certified`.
    """
    k, attributes = k or task.k, sorted(attributes)
    left, right = collapse_queries(queries, attributes), collapse_pool(pool, task, attributes)
    index = list(range(len(attributes)))
    if max_posting is None:
        scored = candidates(left, spread(right), len(index), k, g=g)
    else:
        scored = _from_short_postings(left, right, attributes, g, longest or max(longest_cell(queries, attributes), longest_cell(pool, attributes)), max_posting)
    found = _ranked(scored, k, True).persist()  # k rows a query, read three times
    bound = F.lit(0.0)
    for i in index:
        size = F.length(f"q{i}")
        bound = bound + F.coalesce(F.when(size > 0, F.least(F.lit(1.0), (g - 1) / size)), F.lit(0.0))
    bounds = left.select("cells_id", F.round(bound / max(1, len(attributes)), 9).alias("bound"))
    last = found.groupBy("cells_id").agg(F.max("rank").alias("n"), F.min("similarity").alias("least"))
    sure = bounds.join(last, "cells_id").filter((F.col("n") >= k) & (F.col("least") > F.col("bound"))).select("cells_id")
    if max_posting is None:
        rest = left.join(sure, "cells_id", "left_anti")
        guarded(rest.count(), right.count())
        again = _ranked(candidates(rest, spread(right), len(index), k), k, True)
        found = found.join(sure, "cells_id", "left_semi").unionByName(again)
    out = _for_queries(found, queries, task, attributes)
    if report:
        keyed = queries.select(F.col(task.row_id).alias("query_id"), *(F.col(a).alias(f"q{i}") for i, a in enumerate(attributes)))
        marks = keyed.select("query_id", cells_key([f"q{i}" for i in index]).alias("cells_id")).join(sure.withColumn("certified", F.lit(True)), "cells_id", "left")
        out = out.join(marks.select("query_id", F.coalesce("certified", F.lit(False)).alias("certified")), "query_id")
    return out


def _from_short_postings(left: DataFrame, right: DataFrame, attributes: list[str], g: int, longest: int, max_posting: int) -> DataFrame:
    """Pairs that share a gram which at most max_posting pool rows have, with their similarity."""
    def postings(frame: DataFrame, side: str, key: str) -> DataFrame:
        out = None
        for i in range(len(attributes)):
            part = frame.select(key, F.lit(i).alias("attribute"), F.explode(grams(F.col(f"{side}{i}"), g)).alias("gram"))
            out = part if out is None else out.unionAll(part)
        return out

    numbered = right.withColumn("pool_key", F.xxhash64("example_id", "target_value", *[f"p{i}" for i in range(len(attributes))]))
    of_pool = postings(numbered, "p", "pool_key")
    rare = of_pool.groupBy("attribute", "gram").count().filter(F.col("count") <= max_posting)
    of_pool = of_pool.join(rare, ["attribute", "gram"], "left_semi")
    pairs = postings(left, "q", "cells_id").join(of_pool, ["attribute", "gram"]).select("cells_id", "pool_key").distinct()
    return (spread(pairs).join(left, "cells_id").join(numbered, "pool_key")
            .select("cells_id", "target_value", "example_id", similarity(attributes, longest).alias("similarity")))


def retrieve_random(queries: DataFrame, pool: DataFrame, task: Task, k: int | None = None, per: str = "query", deck: int = 1000) -> DataFrame:
    """Random complete rows. Similarity is null.

    per = `run`: the same k rows, the first by hash, for all queries (broadcast). per = `query`: all complete rows are dealt
    by hash into shuffled decks of about `deck` rows; a query draws one deck by its own hash and k neighbours in it, so
    every row can be drawn and a query meets its deck by an equi-join.
    """
    k = k or task.k
    seed = str(task.seed)
    known = pool.filter(F.col(task.target).isNotNull()).select(F.col(task.row_id).alias("example_id"), F.col(task.target).alias("target_value"))
    order = [hash32(F.col("example_id"), seed), F.col("example_id")]
    asked = queries.select(F.col(task.row_id).alias("query_id"))
    empty = F.lit(None).cast("double").alias("similarity")
    if per == "run":
        top = known.orderBy(*order).limit(k)
        cards = top.select("example_id", "target_value", F.row_number().over(Window.orderBy(*order)).alias("rank"))  # k rows
        return asked.crossJoin(F.broadcast(cards)).select("query_id", "rank", "example_id", "target_value", empty)
    decks = known.agg(F.greatest(F.lit(1), F.floor(F.count("*") / deck)).alias("decks"))  # one row
    in_deck = lambda key: (hash32(F.col(key), seed, "deck") % F.col("decks")).alias("deck")
    dealt = known.crossJoin(F.broadcast(decks)).select("example_id", "target_value", in_deck("example_id"))
    cards = dealt.select("*", (F.row_number().over(Window.partitionBy("deck").orderBy(*order)) - 1).alias("place"))
    sizes = dealt.groupBy("deck").agg(F.count("*").alias("cards"))
    drawn = asked.crossJoin(F.broadcast(decks)).select("query_id", in_deck("query_id")).join(sizes, "deck")
    start = hash32(F.col("query_id"), seed)
    places = drawn.select("query_id", "deck", "cards", F.explode(F.sequence(F.lit(1), F.least(F.lit(k), F.col("cards")).cast("int"))).alias("rank")).withColumn(
        "place", (start + F.col("rank") - 1) % F.col("cards"))
    return places.join(cards, ["deck", "place"]).select("query_id", "rank", "example_id", "target_value", empty)


def retrieve_fixed(queries: DataFrame, pool: DataFrame, task: Task, example_ids: list) -> DataFrame:
    """Examples chosen by hand, in the given order, for every query."""
    order = F.create_map(*[F.lit(x) for i, e in enumerate(example_ids) for x in (e, i + 1)])
    chosen = pool.filter(F.col(task.row_id).isin(*example_ids)).select(
        order[F.col(task.row_id)].alias("rank"), F.col(task.row_id).alias("example_id"), F.col(task.target).alias("target_value"))
    return queries.select(F.col(task.row_id).alias("query_id")).crossJoin(F.broadcast(chosen)).select(
        "query_id", "rank", "example_id", "target_value", F.lit(None).cast("double").alias("similarity"))


def retrieve_embedding(queries: DataFrame, pool: DataFrame, row_id: str, vector: str, target: str, k: int, diverse: bool = False) -> DataFrame:
    """The contrast: cosine similarity of vectors, all pairs by products of blocks; refused beyond PAIR_LIMIT."""
    guarded(queries.count(), pool.count())
    left = queries.select(F.col(row_id).alias("cells_id"), F.col(vector).alias("vector"))
    right = pool.select(F.col(row_id).alias("example_id"), F.col(target).cast("string").alias("target_value"), F.col(vector).alias("vector"))
    scored = vector_candidates(left, spread(right), k, diverse)
    return _ranked(scored, k, diverse).select(F.col("cells_id").alias("query_id"), "rank", "example_id", "target_value", "similarity")


def shared_passages(queries: DataFrame, pool: DataFrame, query_id: str, row_id: str, text: str = "text", least: int = 100, most_blocks: int = 1_000_000) -> DataFrame:
    """Long cells: (query_id, row_id, length) of all pairs whose longest common substring has at least `least` characters.

    A common substring of that length holds a whole block of the query's text, cut every half of `least` characters. The
    blocks' hashes meet those of every window of the other texts: while there are at most most_blocks, the queries are
    broadcast and met in one scan of the pool, else hashes meet by a shuffle. Surviving pairs are measured exactly. Null
    texts share nothing.
    """
    width = (least + 1) // 2
    asked = queries.filter(F.length(text) >= width).select(F.col(query_id).alias("query_id"), F.col(text).alias("t"))
    there = pool.filter(F.length(text) >= width).select(F.col(row_id).alias("row_id"), F.col(text).alias("t"))
    kinds = dict(asked.dtypes)["query_id"], dict(there.dtypes)["row_id"]
    n = asked.agg(F.sum(F.floor(F.length("t") / width))).first()[0] or 0
    if n <= most_blocks:
        shared = pool.sparkSession.sparkContext.broadcast([tuple(r) for r in asked.toLocalIterator()])
        return there.mapInArrow(_passages(shared, width, least), f"query_id {kinds[0]}, row_id {kinds[1]}, length long")
    blocks = asked.mapInArrow(_windows("query_id", width, width), f"query_id {kinds[0]}, window long")
    windows = there.mapInArrow(_windows("row_id", width, 1), f"row_id {kinds[1]}, window long")
    pairs = windows.join(blocks, "window").select("query_id", "row_id").distinct()
    cells = pairs.join(asked.withColumnRenamed("t", "a"), "query_id").join(there.withColumnRenamed("t", "b"), "row_id")
    return spread(cells).select("query_id", "row_id", lcs_len_arrow("a", "b").cast("long").alias("length")).filter(F.col("length") >= least)


def _windows(key: str, width: int, step: int):
    """The distinct hashes of the windows that begin at every step-th character."""
    def run(batches):
        for batch in batches:
            for i, t in zip(batch.column(key), batch.column("t")):
                hashes = np.unique(window_hashes(t.as_py(), width)[::step]).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.repeat(i, len(hashes)), pa.array(hashes)], [key, "window"])

    return run


def _passages(shared, width: int, least: int):
    def run(batches):
        of_block: dict[int, list[int]] = {}
        for i, (_, t) in enumerate(shared.value):
            for x in np.unique(window_hashes(t, width)[::width]).tolist():
                of_block.setdefault(x, []).append(i)
        known = WindowSet(np.array(list(of_block), dtype=np.uint64))
        automata: dict[int, SuffixAutomaton] = {}
        held = 0
        for batch in batches:
            found = []
            for row, t in zip(batch.column("row_id").to_pylist(), batch.column("t")):
                t = t.as_py()
                for i in sorted({i for x in known.found(window_hashes(t, width)).tolist() for i in of_block[x]}):
                    key, item = shared.value[i]
                    if i not in automata:
                        if held > AUTOMATA_CHARS:
                            automata, held = {}, 0
                        automata[i] = SuffixAutomaton(item)
                        held += len(item)
                    length = automata[i].longest_in(t)[0]
                    if length >= least:
                        found.append((key, row, length))
            if found:
                keys, rows, lengths = zip(*found)
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(rows), pa.array(lengths, pa.int64())], ["query_id", "row_id", "length"])

    return run
