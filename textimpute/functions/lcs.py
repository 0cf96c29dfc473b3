"""Longest common substring as a column: a pure SQL expression for short cells, an Arrow function for long ones."""

from __future__ import annotations

import math
from functools import lru_cache

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .automaton import SuffixAutomaton, lcs_string

#: Longest shorter cell that the SQL expression is unrolled for by default.
SHORT = 64
#: Cells up to this many characters are compared by the SQL expression; beyond, the automaton is several times faster
#: (18-character cells: about 44 against 4 microseconds a pair).
EXPRESSION_UP_TO = 6


def lcs_len_expr(a: Column, b: Column, longest: int = SHORT) -> Column:
    """LCS length without Python: strings that share an n-gram share all shorter ones, so the length is bisected.

    longest: bound of the shorter cell's length; it fixes the number of halvings. Null on either side gives 0.
    """
    def grams(s: Column, n: Column) -> Column:
        return F.when(F.length(s) >= n, F.transform(F.sequence(F.lit(1), F.length(s) - n + 1), lambda i: F.substring(s, i, n))).otherwise(F.array())

    def halve(state: Column, _: Column) -> Column:
        middle = F.floor((state["low"] + state["high"] + 1) / 2).cast("int")
        shared = (middle > 0) & F.arrays_overlap(grams(a, middle), grams(b, middle))
        return F.when(state["low"] >= state["high"], state).otherwise(F.struct(
            F.when(shared, middle).otherwise(state["low"]).alias("low"), F.when(shared, state["high"]).otherwise(middle - 1).alias("high")))

    rounds = F.array(*[F.lit(k) for k in range(math.ceil(math.log2(longest + 1)) + 1)])
    start = F.struct(F.lit(0).alias("low"), F.least(F.length(a), F.length(b)).alias("high"))
    return F.coalesce(F.aggregate(rounds, start, halve)["low"], F.lit(0))


@lru_cache(maxsize=64)
def _automaton(text: str) -> SuffixAutomaton:
    return SuffixAutomaton(text)


def _lengths(a: pd.Series, b: pd.Series) -> pd.Series:
    # one automaton per distinct text of the side with fewer texts; the other side streams through it
    if b.nunique() < a.nunique():
        a, b = b, a
    out = pd.Series(0, index=a.index, dtype="int64")
    for text, rows in a.groupby(a).groups.items():
        if text:
            automaton = _automaton(text)
            out[rows] = [automaton.longest_in(o)[0] if isinstance(o, str) else 0 for o in b[rows]]
    return out


@F.pandas_udf(T.IntegerType())
def lcs_len_arrow(a: pd.Series, b: pd.Series) -> pd.Series:
    return _lengths(a, b)


@F.pandas_udf(T.StringType())
def lcs_str(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([lcs_string(x, y) if isinstance(x, str) and isinstance(y, str) else "" for x, y in zip(a, b)])


def lcs_len(a: Column, b: Column, longest: int | None) -> Column:
    """The way that suits cells of at most `longest` characters (None: unknown)."""
    return lcs_len_expr(a, b, longest) if longest is not None and longest <= EXPRESSION_UP_TO else lcs_len_arrow(a, b)


def cell_similarity(a: Column, b: Column, longest: int | None) -> Column:
    """LCS length over the longer length; 0 for a null or where both are empty."""
    size = F.greatest(F.length(a), F.length(b))
    return F.coalesce(F.when(a.isNotNull() & b.isNotNull() & (size > 0), lcs_len(a, b, longest) / size), F.lit(0.0))


def register(spark: SparkSession) -> None:
    """SQL names: lcs_len, lcs_str, lcs_sim, rouge1_f1, common_substring (aggregate) and the table function
    shared_substrings(a, b, min_len)."""
    from . import sqlnames

    sqlnames.register(spark)
