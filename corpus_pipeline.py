"""The corpus pipeline: language ID, quality rules, near-duplicates, benchmark decontamination, packing.

Each stage takes (spark, docs, sf_dir), works on every document its predecessor kept, and all but the last return the
columns of documents. run() writes each stage's result as Parquet in the shared folder and reads it again for the next.

ORACLE_SQL is None: the models of stages 1 and 2 and the fingerprints of stage 3 cannot be expressed in SQL. The tests hold
each stage against a plain version of it.

Stages keep repeated rows apart, treat nulls as their operators say, and pass on columns they do not know.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textimpute.llm import decontam, langid, packing, quality, simhash
from textimpute.llm.common import free_prefix, read_table, ship, written


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the calibrated model accepts."""
    ship(spark)
    model = langid.fit(langid.learning_rows(docs))
    p = free_prefix(docs, ["lang_pred", "score", "rejected"])
    return langid.predicted(docs, model, prefix=p).filter(~F.col(f"{p}rejected")).select(*docs.columns)


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and the likelihood ratio."""
    ratio = quality.fit(docs, read_table(spark, sf_dir, "labels"))
    p = free_prefix(docs, ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "score", "kept"])
    return quality.judged(docs, ratio, prefix=p).filter(F.col(f"{p}kept")).select(*docs.columns)


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates (five-word shingles, similarity 0.8 or more): that with the smallest
    doc_id. A row is known by its doc_id and text; rows without a doc_id cannot be named and stay."""
    groups = simhash.near_duplicates(docs.select("doc_id", "text"))
    return simhash.one_of_each(docs, groups)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the spans they share with benchmark items; documents that are mostly such spans go."""
    p = free_prefix(docs, ["n_words", "n_hit", "n_items", "items_sha256", "contaminated", "clean_text", "over_coverage"])
    checked = decontam.scan_documents(docs, read_table(spark, sf_dir, "benchmark"), prefix=p)
    clean = checked.filter(~F.col(f"{p}over_coverage"))
    changed, text = F.col(f"{p}contaminated"), F.col(f"{p}clean_text")
    columns = [F.when(changed, text).otherwise(F.col("text")).alias("text") if c == "text"
               else F.when(changed, F.length(text).cast(docs.schema[c].dataType)).otherwise(F.col(c)).alias(c) if c == "n_chars"
               else F.col(c) for c in docs.columns]
    return clean.select(*columns)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece with its sequence and offset."""
    ship(spark)
    return packing.packed(docs.select("doc_id", "text"))


STAGES = [
    ("language_id", language_id),
    ("quality_rules", quality_rules),
    ("simhash_near_dedup", simhash_near_dedup),
    ("benchmark_decontamination", benchmark_decontamination),
    ("best_fit_packing", best_fit_packing),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
