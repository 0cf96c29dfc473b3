"""Connected components of an edge table, wholly in DataFrame operations.

Alternates two star steps: the large one links each node's larger neighbours to its smallest neighbour, the small one
links its smaller neighbours to that. Every step is a partial-aggregate minimum and one equi-join: a node with very many
edges is summed before the shuffle, and its edges are dealt over several tasks of the join. Stars shrink the longest path
geometrically; each round is written to the shared folder and an order-free digest of it ends the loop.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hot_join, removed, written


def _star(edges: DataFrame, rows: int, larger: bool) -> DataFrame:
    u, v = F.col("u"), F.col("v")
    if larger:
        near = edges.select(u, v).unionAll(edges.select(v.alias("u"), u.alias("v")))
    else:
        near = edges.select(F.greatest(u, v).alias("u"), F.least(u, v).alias("v"))
    least = near.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select(F.col("u").alias("k"), F.least("u", "m").alias("m"), "n")
    joined = hot_join(near, least, "u", "k", "n", rows)
    if larger:
        out = joined.filter(v > u).select(v.alias("u"), F.col("m").alias("v"))
    else:
        out = joined.select(v.alias("u"), F.col("m").alias("v")).unionAll(least.select(F.col("k").alias("u"), F.col("m").alias("v")))
    return out.filter("u <> v").distinct()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(u, v) edges over one orderable type -> (node, component): component is the smallest node reachable.

    Nulls and self-loops are ignored; a node without an edge has no row. Raises if max_rounds does not suffice
    (path length halves at least every other round, so 60 rounds cover any graph that fits a cluster).
    """
    now = written(edges.select("u", "v").filter("u is not null and v is not null and u <> v")
                  .select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    state = None
    for _ in range(max_rounds):
        digest = now.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("h")).first()
        if (digest["n"], digest["h"]) == state or not digest["n"]:
            stars = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
            return stars.unionAll(stars.select("component", "component").toDF("node", "component")).distinct()
        state = (digest["n"], digest["h"])
        half = written(_star(now, digest["n"], True), "edges")
        after = written(_star(half, digest["n"], False), "edges")
        removed(edges.sparkSession, half), removed(edges.sparkSession, now)
        now = after
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
