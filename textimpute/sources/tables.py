"""Tables of the experiments: the given ones and those derived from them by pure functions of their keys."""

from __future__ import annotations

import os
import re
import tempfile
import uuid
import zipfile

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import as_text, hash32


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_typed(spark: SparkSession, path: str, schema: str, fmt: str = "csv", **options) -> DataFrame:
    """CSV or JSON with a stated schema (never inferred)."""
    return spark.read.format(fmt).schema(schema).options(**({"header": True} if fmt == "csv" else {}) | options).load(path)


def shared_folder(spark: SparkSession, label: str) -> str:
    """A fresh path in the folder that driver and executors share: that of spark.checkpoint.dir. Only where driver and
    executors are one process may it be unset; then an own folder is set."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = tempfile.mkdtemp(prefix="textimpute-shared-")
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def save_evidence(patterns: DataFrame, path: str) -> None:
    """Patterns as Parquet, one folder an attribute, so that a later read prunes to the attributes it needs."""
    patterns.write.mode("overwrite").partitionBy("attribute").parquet(path)


def phone_of(custkey: Column, nationkey: Column) -> Column:
    """A phone number whose area code follows from the nation, in one of four formats."""
    h = hash32(custkey, "phone")
    code = (200 + 31 * nationkey).cast("string")
    p3 = F.lpad((h % 1000).cast("string"), 3, "0")
    p4 = F.lpad((F.floor(h / 1000) % 10000).cast("string"), 4, "0")
    shape = F.floor(h / 10000000) % 4
    return (F.when(shape == 0, F.concat_ws("-", code, p3, p4))
            .when(shape == 1, F.concat(F.lit("("), code, F.lit("-) "), p3, F.lit(" "), p4))
            .when(shape == 2, F.concat(code, F.lit("/"), p3, F.lit("-"), p4))
            .otherwise(F.concat(F.lit("+1"), code, F.lit(" "), p3, p4)))


def geo_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers with phone and reviews; target n_name."""
    customer, nation, region, documents = (load(spark, sf_dir, t) for t in ("customer", "nation", "region", "documents"))
    size = documents.agg(F.count("*").alias("n_docs"))
    h = hash32(F.col("c_custkey"), "phone")
    text = documents.select(F.col("doc_id"), F.substring("text", 1, 120).alias("review"))
    return (customer.join(F.broadcast(nation), customer["c_nationkey"] == nation["n_nationkey"])
            .join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
            .crossJoin(F.broadcast(size))  # one row
            .join(text, F.col("c_custkey") % F.col("n_docs") == F.col("doc_id"), "left")
            .select("c_custkey", "n_name", phone_of(F.col("c_custkey"), F.col("c_nationkey")).alias("c_phone"),
                    F.concat(F.lit("Rated "), (1 + h % 5).cast("string"), F.lit(".0: "), F.coalesce("review", F.lit(""))).alias("c_reviews"),
                    "c_name", "r_name", "c_mktsegment", as_text(customer, "c_acctbal").alias("c_acctbal")))


def titled(part: DataFrame) -> DataFrame:
    k = F.col("p_partkey") % 3
    title = (F.when(k == 0, F.concat_ws(" ", "p_brand", "p_name", "p_type"))
             .when(k == 1, F.concat(F.col("p_name"), F.lit(" by "), F.col("p_brand"), F.lit(", "), F.col("p_type")))
             .otherwise(F.concat(F.col("p_type"), F.lit(" "), F.col("p_name"), F.lit(" ("), F.col("p_brand"), F.lit(")"))))
    return part.withColumn("p_title", title)


def part_titles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts with a title that names the brand; target p_brand."""
    part = titled(load(spark, sf_dir, "part"))
    return part.select("p_partkey", "p_brand", "p_title", "p_name", "p_type", F.col("p_size").cast("string").alias("p_size"),
                       as_text(part, "p_retailprice").alias("p_retailprice"))


#: The order lines' own keys: an order may hold one line number more than once.
LINE_KEYS = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")

WIDE_CANDIDATES = ("c_phone", "c_reviews", "c_name", "c_mktsegment", "c_acctbal", "o_orderstatus", "o_orderpriority", "o_totalprice",
                   "o_orderdate", "l_quantity", "l_returnflag", "l_shipdate", "p_name", "p_brand", "p_type", "s_name")


def wide_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with 16 candidate attributes; target n_name (of the customer)."""
    lines, orders, part, supplier = (load(spark, sf_dir, t) for t in ("lineitem", "orders", "part", "supplier"))
    geo = geo_customer(spark, sf_dir).drop("r_name")
    joined = (lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"]).join(geo, F.col("o_custkey") == F.col("c_custkey"))
              .join(part.select("p_partkey", "p_name", "p_brand", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
              .join(supplier.select("s_suppkey", "s_name"), F.col("l_suppkey") == F.col("s_suppkey")))
    return joined.select(F.concat_ws("-", *LINE_KEYS).alias("row_id"), "n_name", "c_custkey",
                         *(as_text(joined, c).alias(c) for c in WIDE_CANDIDATES))


def mobile_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with the part's titles, the largest table; target p_brand."""
    lines, part = load(spark, sf_dir, "lineitem"), titled(load(spark, sf_dir, "part"))
    joined = lines.join(part, lines["l_partkey"] == part["p_partkey"])
    return joined.select(F.concat_ws("-", *LINE_KEYS).alias("row_id"), "p_brand", "p_title", "p_name", "p_type",
                         F.col("p_size").cast("string").alias("p_size"), as_text(joined, "l_quantity").alias("l_quantity"))


def pages_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Web pages with language and host taken out of the url; targets lang and host."""
    url, html = F.col("url"), F.col("html")
    host = F.regexp_extract(url, r"://([^/?#]+)", 1)
    return load(spark, sf_dir, "pages").select(
        "page_id", F.regexp_extract(url, r"://[^/]+/([a-z]{2})/", 1).alias("lang"), host.alias("host"), "url", "html",
        F.regexp_extract(html, r"(?s)<title>(.*?)</title>", 1).alias("title"),
        F.trim(F.regexp_replace(F.regexp_replace(html, r"(?s)<(script|style)\b.*?</\1>", " "), r"(?s)<[^>]*>", " ")).alias("body"),
        F.regexp_extract(host, r"\.([a-z]+)$", 1).alias("tld"))


def lengths(spark: SparkSession, m: int, n: int, length: int) -> DataFrame:
    """m groups of n rows whose cells have `length` characters: a core shared by the group, the rest hashes."""
    group, row = F.floor(F.col("id") / n), F.col("id")
    core = F.substring(F.md5(F.concat(F.lit("core"), group.cast("string"))), 1, max(4, min(16, length // 2)))
    filler = F.array_join(F.transform(F.sequence(F.lit(0), F.lit(length // 32 + 1)), lambda i: F.md5(F.concat_ws("|", row, i))), "")
    return spark.range(m * n).select(F.col("id").alias("row_id"), F.concat(F.lit("g"), group.cast("string")).alias("target"),
                                     F.substring(F.concat(core, filler), 1, length).alias("value"))


_sent: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Lets workers import this package even where the repository is not on their path."""
    context = spark.sparkContext
    if context.applicationId in _sent:
        return
    _sent.add(context.applicationId)
    top = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    target = os.path.join(os.path.realpath(tempfile.mkdtemp()), f"{os.path.basename(top)}_package.zip")
    with zipfile.ZipFile(target, "w") as z:
        for folder, _, names in os.walk(top):
            for n in names:
                if n.endswith(".py"):
                    full = os.path.join(folder, n)
                    z.write(full, os.path.relpath(full, os.path.dirname(top)))
    context.addPyFile(target)


def shipped(f):
    """The query with the package sent to the workers first."""
    def run(spark: SparkSession, *args):
        ship(spark)
        return f(spark, *args)

    run.__doc__ = f.__doc__
    return run
