"""SQL names of the text functions."""

from __future__ import annotations

from collections import Counter

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .automaton import SuffixAutomaton
from .lcs import _lengths, lcs_len_arrow, lcs_str


@F.pandas_udf(T.DoubleType())
def lcs_sim(a: pd.Series, b: pd.Series) -> pd.Series:
    size = pd.concat([a.str.len(), b.str.len()], axis=1).max(axis=1, skipna=False)
    return (_lengths(a, b) / size.where(size > 0)).fillna(0.0)


def _unigrams(text) -> Counter:
    return Counter("".join(c if c.isalnum() else " " for c in (text or "").lower()).split())


@F.pandas_udf(T.DoubleType())
def rouge1_f1(predicted: pd.Series, truth: pd.Series) -> pd.Series:
    out = []
    for p, t in zip(predicted, truth):
        a, b = _unigrams(p), _unigrams(t)
        both = sum((a & b).values())
        out.append(2 * both / (sum(a.values()) + sum(b.values())) if both else 0.0)
    return pd.Series(out)


@F.pandas_udf(T.StringType())
def common_substring(value: pd.Series, share: pd.Series) -> str:
    """The longest substring (first in text order) in at least the given share of a group's rows; '' if none."""
    texts = [v for v in value if isinstance(v, str)]
    found = SuffixAutomaton(*texts).maximal(max(1e-9, float(share.iloc[0]) * len(value))) if texts else []
    return min(found, key=lambda x: (-len(x[0]), x[0]))[0] if found else ""


@F.udtf(returnType=T.StructType().add("pattern", "string").add("length", "integer"))
class SharedSubstrings:
    """Maximal substrings of at least min_len characters that two texts share."""

    def eval(self, a: str, b: str, min_len: int):
        if a and b:
            for pattern, _ in SuffixAutomaton(a, b).maximal(2):
                if len(pattern) >= min_len:
                    yield pattern, len(pattern)


@F.udtf(returnType=T.StructType().add("pattern", "string").add("support", "integer"))
class GroupPatterns:
    """Maximal substrings in at least a share q of the texts of an array: the patterns of one group."""

    def eval(self, texts: list, q: float):
        known = [t for t in texts or [] if t is not None]
        for pattern, support in SuffixAutomaton(*known).maximal(max(1e-9, q * len(texts))) if known else []:
            yield pattern, support


def register(spark: SparkSession) -> None:
    spark.udf.register("lcs_len", lcs_len_arrow)
    spark.udf.register("lcs_str", lcs_str)
    spark.udf.register("lcs_sim", lcs_sim)
    spark.udf.register("rouge1_f1", rouge1_f1)
    spark.udf.register("common_substring", common_substring)
    spark.udtf.register("shared_substrings", SharedSubstrings)
    spark.udtf.register("group_patterns", GroupPatterns)
