"""What the operators share: byte-level words, the shared folder, written intermediate tables."""

from __future__ import annotations

import ctypes
import os
import re
import tempfile
import uuid
import zipfile
import zlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes that end a word where words are runs of anything but ASCII letters and digits are cut: everything below 0x80
#: that is no letter or digit becomes a blank, A-Z becomes a-z. Bytes of longer UTF-8 sequences stay.
ALNUM_TABLE = bytes(
    b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256)
)


def alnum_words(text: bytes) -> list[bytes]:
    """Lower-cased words of ASCII letters, digits and non-ASCII characters."""
    return text.translate(ALNUM_TABLE).split()


def blank_words(text: bytes) -> list[bytes]:
    """Words between the six ASCII blanks, as they stand (bytes.split() cuts at exactly these)."""
    return text.split()


def as_bytes(column) -> list[bytes | None]:
    """UTF-8 bytes of an Arrow string column, without a detour over str."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_string(column.type):
        column = column.cast(pa.binary())
    elif pa.types.is_large_string(column.type):
        column = column.cast(pa.large_binary())
    return column.to_pylist()


def small(batches: Iterator[pa.RecordBatch], most_bytes: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The batches cut into pieces of about most_bytes, and freed memory given back when they end: Python objects of a
    whole batch of texts take several times its bytes, and workers live longer than their tasks."""
    try:
        for b in batches:
            rows = max(1, int(len(b) * most_bytes / max(1, b.nbytes)))
            for at in range(0, len(b), rows):
                yield b.slice(at, rows)
    finally:
        give_back()


def give_back() -> None:
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def crc_mod(column: Column, n: int) -> Column:
    """crc32 of the value as text, modulo n; null for null."""
    return F.pmod(F.crc32(F.encode(column.cast("string"), "UTF-8")), F.lit(n))


def crc_of(value) -> int:
    return zlib.crc32(str(value).encode())


def with_fields(schema: T.StructType, **kinds: str | T.DataType) -> T.StructType:
    """schema and further fields (a DataFrame's own schema object must not be changed)."""
    out = T.StructType(list(schema.fields))
    for name, kind in kinds.items():
        out = out.add(name, kind)
    return out


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Lets workers import this package even where the repository is not on their path."""
    context = spark.sparkContext
    if context.applicationId in _shipped:
        return
    _shipped.add(context.applicationId)
    top = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    target = os.path.join(os.path.realpath(tempfile.mkdtemp()), f"{os.path.basename(top)}_src.zip")
    with zipfile.ZipFile(target, "w") as z:
        for folder, _, names in os.walk(top):
            for n in names:
                if n.endswith(".py"):
                    full = os.path.join(folder, n)
                    z.write(full, os.path.relpath(full, os.path.dirname(top)))
    context.addPyFile(target)


def shared_folder(spark: SparkSession, label: str) -> str:
    """A fresh path in the folder that driver and executors share (spark.checkpoint.dir; own one only if unset, and only
    where driver and executors are one process)."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = tempfile.mkdtemp(prefix="textimpute-shared-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str) -> DataFrame:
    """df as a table written in the shared folder: cuts lineage and outlives executors."""
    spark = df.sparkSession
    path = shared_folder(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def free_prefix(df: DataFrame, names: Iterable[str], prefix: str = "__") -> str:
    """A prefix under which none of the names is a column of df (names are compared without case)."""
    taken = {c.lower() for c in df.columns}
    while any((prefix + n).lower() in taken for n in names):
        prefix += "_"
    return prefix


def hot_join(left: DataFrame, right: DataFrame, left_key: str, right_key: str, weight: str, rows: int, how: str = "inner") -> DataFrame:
    """left joined to right, which has one row a key and in `weight` the number of left's rows with that key.

    Keys with more than a two-thousandth of `rows` (so fewer than 2000 keys, which are broadcast) are dealt over several
    tasks: left's rows get a salt, right's row is repeated for each. The column of weights is dropped.
    """
    cut = max(1000, rows // 2000)
    parts = F.ceil(F.col(weight) / cut).cast("int")
    heavy = right.filter(F.col(weight) > cut).select(F.col(right_key).alias("__hot"), parts.alias("__parts"))
    dealt = left.join(F.broadcast(heavy), F.col(left_key) == F.col("__hot"), "left").withColumn(
        "__salt", F.when(F.col("__parts").isNotNull(), F.pmod(F.monotonically_increasing_id(), F.col("__parts"))).otherwise(F.lit(0)).cast("int"))
    repeated = right.withColumn("__copy", F.explode(F.when(F.col(weight) > cut, F.sequence(F.lit(0), parts - 1)).otherwise(F.array(F.lit(0))))).drop(weight)
    same = (F.col(left_key) == F.col(right_key)) & (F.col("__salt") == F.col("__copy"))
    return dealt.join(repeated, same, how).drop("__hot", "__parts", "__salt", "__copy")


def removed(spark: SparkSession, df: DataFrame) -> None:
    """Deletes the files of a table made by written() that nothing reads any more."""
    jvm = spark.sparkContext._jvm
    for f in {os.path.dirname(x) for x in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(f)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
