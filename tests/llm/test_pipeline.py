"""The pipeline's stages, each on what its predecessor kept."""

import corpus_pipeline as cp
from textimpute.llm import decontam, simhash
from textimpute.llm.common import read_table, written
from textimpute.llm.queries import QUERIES


def test_stages(spark, sf):
    docs = read_table(spark, sf, "documents")
    bench = read_table(spark, sf, "benchmark")
    seen = [docs]
    for name, stage in cp.STAGES:
        seen.append(written(stage(spark, seen[-1], sf), name))
        if name != "best_fit_packing":
            assert seen[-1].columns == docs.columns
    ids = [{r[0] for r in d.select("doc_id").collect()} for d in seen]
    assert ids[1] <= ids[0] and ids[2] <= ids[1] and ids[3] <= ids[2] and ids[4] <= ids[3] and ids[5] == ids[4]
    assert len(ids[1]) > 0.97 * len(ids[0])
    # one document of each group stays
    groups = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(seen[2].select("doc_id", "text")).collect()}
    assert ids[3] == {i for i, c in groups.items() if i == c}
    # no window of a benchmark item is left, texts without one are as they were
    assert decontam.scan_documents(seen[4], bench).filter("contaminated").count() == 0
    before = {r["doc_id"]: r["text"] for r in seen[3].collect()}
    hit = {r["doc_id"] for r in decontam.scan_documents(seen[3], bench).filter("contaminated").collect()}
    for r in seen[4].collect():
        assert r["doc_id"] in hit or r["text"] == before[r["doc_id"]]
        assert r["n_chars"] == len(r["text"]) or r["doc_id"] not in hit
    assert QUERIES["pipeline"](spark, sf).count() == seen[5].count()


def test_stages_stand_nulls_repeats_and_empty_tables(spark, sf):
    docs = read_table(spark, sf, "documents")
    odd = docs.unionByName(docs.limit(3)).unionByName(spark.createDataFrame(
        [(None, None, None, None, None), (None, "some words here", "en", "s", 15), (900001, None, "en", "s", None), (900002, "", None, None, 0), (900003, "word " * 40_000, "en", "s", 200_000)], docs.schema))
    for start in (odd, docs.limit(0)):
        now = start
        for name, stage in cp.STAGES:
            now = written(stage(spark, now, sf), name)
        assert now.count() >= 0


CLASHING = ("n_words", "n_hit", "n_items", "items_sha256", "contaminated", "clean_text", "over_coverage", "__kept", "__rejected", "__score", "__spans", "__items",
            "__doc", "__mark", "__gone", "lang_pred", "score", "rejected", "kept", "base_failed", "seq", "f0", "id", "mark", "component_id", "stays", "key", "sequence_id")


def test_stages_pass_on_columns_that_clash_with_their_own(spark, sf):
    from pyspark.sql import functions as F

    docs = read_table(spark, sf, "documents")
    plain, extra = docs, docs.withColumns({c: F.lit(k) for k, c in enumerate(CLASHING)})
    for name, stage in cp.STAGES:
        plain, extra = written(stage(spark, plain, sf), name), written(stage(spark, extra, sf), name)
        if name != "best_fit_packing":
            assert extra.columns == [*docs.columns, *CLASHING]
            assert sorted(map(str, extra.select(docs.columns).collect())) == sorted(map(str, plain.collect()))
    assert extra.count() == plain.count() > 0
