"""Column expressions on text: canonical text of any type, seeded hashes, serialisation, token counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

PLACEHOLDERS = ("", "null", "n/a", "none", "nan", "?")


def as_text(df: DataFrame, name: str) -> Column:
    """The column as text that reads alike in every engine."""
    kind, c = df.schema[name].dataType, F.col(name)
    if isinstance(kind, T.StringType):
        return c
    if isinstance(kind, (T.DoubleType, T.FloatType, T.DecimalType)):
        return F.round(c, 2).cast("decimal(18,2)").cast("string")
    if isinstance(kind, T.TimestampType):
        return F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    if isinstance(kind, T.DateType):
        return F.date_format(c, "yyyy-MM-dd")
    if isinstance(kind, (T.ArrayType, T.MapType, T.StructType)):
        return F.to_json(c)
    return c.cast("string")


def hash32(*parts: Column | str) -> Column:
    """First 32 bits of the md5 of the parts joined by `|`: a bigint that other engines compute alike."""
    columns = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[c.cast("string") for c in columns])), 1, 8), 16, 10).cast("bigint")


def normalise_missing(df: DataFrame, columns: list[str], placeholders=PLACEHOLDERS) -> DataFrame:
    """Placeholders of a missing value become null."""
    return df.withColumns({c: F.when(~F.lower(F.trim(F.col(c).cast("string"))).isin(*placeholders), F.col(c)) for c in columns})


def serialise(columns: dict[str, Column]) -> Column:
    """`name: value` pairs joined by `; `; missing cells are left out."""
    return F.concat_ws("; ", *[F.concat(F.lit(f"{n}: "), c) for n, c in columns.items()])


def words_in(text: Column) -> Column:
    """Number of blank-separated words; a stand-in for a language model's tokens."""
    return F.size(F.filter(F.split(F.coalesce(text, F.lit("")), r"[ \t\n\r]+"), lambda w: w != "")).cast("long")


def unigrams(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")
