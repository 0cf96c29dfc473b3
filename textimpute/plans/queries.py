"""Named queries over the given tables: methods, variants, baselines, measures and workloads."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.lcs import lcs_len_arrow, lcs_len_expr, lcs_str
from ..functions.text import hash32
from ..operators import backends, baselines, blocks, compare, dependency, metrics, missingness, patterns, problem, prompting, retrieval, sampling
from ..operators.impute import explain, impute, impute_many
from ..operators.problem import Task
from ..sources import tables
from ..streaming import stream
from .planner import retrieve_planned

GEO = Task("n_name", "c_custkey", ("c_phone", "c_reviews", "c_name", "r_name", "c_mktsegment", "c_acctbal"))
SHORT_GEO = GEO.but(candidates=("c_phone", "c_name", "c_mktsegment", "c_acctbal", "r_name"))
SUPPLY = Task("n_name", "s_suppkey", ("s_phone", "s_name"), m=None, n=None)
PARTS = Task("p_brand", "p_partkey", ("p_title", "p_name", "p_type", "p_size", "p_retailprice"))
GRID = (0.25, 0.5, 0.75)

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}


def query(name: str):
    def put(f: Query) -> Query:
        QUERIES[name] = f
        return f
    return put


def suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers with a phone number by the rule of the customers' ones; target n_name."""
    supplier, nation = tables.load(spark, sf_dir, "supplier"), tables.load(spark, sf_dir, "nation")
    return supplier.join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey")).select(
        "s_suppkey", "n_name", tables.phone_of(F.col("s_suppkey"), F.col("s_nationkey")).alias("s_phone"), "s_name")


def supply_parts(spark: SparkSession, sf_dir: str, seed: int = 1, rate: float = 0.1) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(masked suppliers, queries, pool, truth)."""
    masked, truth = missingness.mask_mcar(suppliers(spark, sf_dir), SUPPLY, rate, seed)
    queries, pool = problem.split(masked, SUPPLY)
    return masked, queries, pool, truth


REGIONS = Task("r_name", "s_suppkey", ("s_phone",), m=None, n=None)


def _regions(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(suppliers with their regions, a tenth of them missing; queries; pool)."""
    nation, region = tables.load(spark, sf_dir, "nation"), tables.load(spark, sf_dir, "region")
    of_nation = nation.join(region, F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_name").alias("nation"), "r_name")
    table = suppliers(spark, sf_dir).join(of_nation, F.col("n_name") == F.col("nation")).drop("nation", "n_name")
    masked, _ = missingness.mask_mcar(table, REGIONS, 0.1, 1)
    return masked, *problem.split(masked, REGIONS)


def geo_masked(spark: SparkSession, sf_dir: str, rate: float = 0.1, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    return missingness.mask_mcar(tables.geo_customer(spark, sf_dir), GEO, rate, seed)


# ------------------------------------------------------------------ set-up
@query("split_missing")
def _(spark, d):
    masked, _ = geo_masked(spark, d)
    return masked.groupBy(F.when(F.col("n_name").isNull(), "query").otherwise("pool").alias("part")).agg(F.count("*").alias("rows"))


for _rate in (10, 20, 30, 40, 50):
    QUERIES[f"mask_mcar_{_rate}"] = lambda spark, d, rate=_rate: geo_masked(spark, d, rate / 100)[0].select("c_custkey", "n_name", "is_masked")


@query("mask_mar")
def _(spark, d):
    geo = tables.geo_customer(spark, d)
    return missingness.mask_mar(geo, GEO, F.col("c_mktsegment") == "BUILDING", 0.3, 0.05)[0].select("c_custkey", "n_name", "is_masked")


@query("mask_mnar")
def _(spark, d):
    geo = tables.geo_customer(spark, d)
    return missingness.mask_mnar(geo, GEO, F.col("n_name").isin("NATION_1", "NATION_2"), 0.5, 0.05)[0].select("c_custkey", "n_name", "is_masked")


@query("mask_by_group")
def _(spark, d):
    return missingness.mask_by(tables.geo_customer(spark, d), GEO, "c_mktsegment", 0.4)[0].select("c_custkey", "n_name", "is_masked")


@query("mask_candidates")
def _(spark, d):
    return missingness.mask_candidates(tables.geo_customer(spark, d), GEO, ["c_phone", "c_name"], 0.2).select("c_custkey", "c_phone", "c_name")


@query("assumption_profile")
def _(spark, d):
    masked, _ = geo_masked(spark, d)
    task = GEO.but(candidates=("c_phone", "c_name"))
    return problem.diagnose(missingness.mask_candidates(masked, task, ["c_phone"], 0.2), task)


# ------------------------------------------------------------------ sampling
@query("group_sizes")
def _(spark, d):
    return sampling.group_sizes(geo_masked(spark, d)[0], GEO)


@query("group_sample_full")
def _(spark, d):
    return sampling.sample_groups(tables.geo_customer(spark, d), GEO.but(m=5, n=10)).select("c_custkey", "n_name")


@query("group_sample_shortfall")
def _(spark, d):
    return sampling.sample_groups(tables.geo_customer(spark, d), GEO.but(m=4, n=65)).select("c_custkey", "n_name")


@query("uniform_sample")
def _(spark, d):
    return sampling.sample_uniform(tables.geo_customer(spark, d), GEO, 100).select("c_custkey", "n_name")


def _lang_task(candidates=("n_chars",)) -> Task:
    return Task("lang", "doc_id", candidates, m=3, n=5)


@query("sample_coverage")
def _(spark, d):
    docs = tables.geo_customer(spark, d)
    task = GEO.but(m=20, n=3)
    a = sampling.coverage(sampling.sample_groups(docs, task), docs, task).withColumn("method", F.lit("groups"))
    return a.unionByName(sampling.coverage(sampling.sample_uniform(docs, task, 60), docs, task).withColumn("method", F.lit("rows")))


# ------------------------------------------------------------------ patterns and dependencies
def _fractions(df: DataFrame, task: Task, mode: str = "maximal") -> DataFrame:
    return dependency.measure(problem.checked(df, task).filter(F.col(task.target).isNotNull()), task, mode)[0]


def _nation(spark, d) -> DataFrame:
    return tables.load(spark, d, "nation").join(tables.load(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(
        F.col("n_nationkey").cast("string").alias("n_nationkey"), F.col("n_regionkey").cast("string").alias("n_regionkey"), "n_name", "r_name", F.col("n_nationkey").alias("id"))


@query("nation_patterns")
def _(spark, d):
    task = Task("n_name", "id", ("n_nationkey",), m=None, n=None)
    found = patterns.mine_frequent(patterns.unpivot_sample(_nation(spark, d), task), task.q, "all")
    return patterns.drop_contained(patterns.unique_patterns(found))


@query("nation_dependency")
def _(spark, d):
    return _fractions(_nation(spark, d), Task("n_name", "id", ("n_nationkey", "r_name"), m=None, n=None))


@query("nation_key_dependency")
def _(spark, d):
    return _fractions(_nation(spark, d), Task("n_nationkey", "id", ("n_name",), m=None, n=None))


@query("region_dependency")
def _(spark, d):
    return _fractions(_nation(spark, d), Task("r_name", "id", ("n_regionkey", "n_name"), m=None, n=None))


def _phone_long(spark, d) -> DataFrame:
    return patterns.unpivot_sample(tables.geo_customer(spark, d), GEO.but(candidates=("c_phone",)))


@query("phone_frequent")
def _(spark, d):
    return patterns.mine_frequent(_phone_long(spark, d), 0.75, "all")


@query("phone_frequent_native")
def _(spark, d):
    return patterns.mine_frequent_native(_phone_long(spark, d), 0.75)


@query("phone_unique")
def _(spark, d):
    return patterns.unique_patterns(patterns.mine_frequent(_phone_long(spark, d), 0.75, "all"))


@query("phone_maximal")
def _(spark, d):
    return patterns.drop_contained(patterns.unique_patterns(patterns.mine_frequent(_phone_long(spark, d), 0.75)))


@query("phone_longest")
def _(spark, d):
    return patterns.mine_frequent(_phone_long(spark, d), 0.25, "longest")


@query("phone_longest_unique")
def _(spark, d):
    long = _phone_long(spark, d)
    return patterns.unique_for(patterns.mine_frequent(long, 0.25, "longest"), long, 0.25, "longest")


@query("phone_pairwise_unique")
def _(spark, d):
    long = patterns.unpivot_sample(suppliers(spark, d), SUPPLY.but(candidates=("s_phone",)))
    return patterns.unique_for(patterns.mine_frequent(long, 0.75, "pairwise"), long, 0.75, "pairwise")


@query("phone_short_unique")
def _(spark, d):
    """Patterns of at most three characters: the limit makes the rows decide on uniqueness."""
    long = _phone_long(spark, d)
    return patterns.unique_in_rows(patterns.mine_frequent(long, 0.75, "all", max_len=3), long, 0.75)


@query("phone_all_rows")
def _(spark, d):
    return patterns.mine_frequent(_phone_long(spark, d), 1.0, "all")


@query("phone_pairwise")
def _(spark, d):
    return patterns.mine_frequent(patterns.unpivot_sample(suppliers(spark, d), SUPPLY.but(candidates=("s_phone",))), 0.75, "pairwise")


@query("phone_recheck_full")
def _(spark, d):
    geo = tables.geo_customer(spark, d)
    long = patterns.unpivot_sample(geo, GEO.but(candidates=("c_phone",)))
    kept = patterns.drop_contained(patterns.unique_patterns(patterns.mine_frequent(long, 0.75)))
    return patterns.recheck_full(geo, kept, GEO.but(candidates=("c_phone",)))


@query("geo_dependency")
def _(spark, d):
    return _fractions(tables.geo_customer(spark, d), SHORT_GEO.but(m=None, n=None))


@query("geo_dependency_sampled")
def _(spark, d):
    return _fractions(tables.geo_customer(spark, d), SHORT_GEO)


@query("geo_region_dependency")
def _(spark, d):
    return _fractions(tables.geo_customer(spark, d), Task("r_name", "c_custkey", ("c_phone",), m=None, n=None))


@query("geo_selection")
def _(spark, d):
    chosen = dependency.select_attributes(problem.checked(tables.geo_customer(spark, d), GEO), GEO)
    return chosen.evidence.withColumn("kept", F.col("attribute").isin(chosen.attributes))


@query("pages_url_dependency")
def _(spark, d):
    return _fractions(tables.pages_flat(spark, d), Task("lang", "page_id", ("url", "host", "tld"), m=None, n=None))


@query("pages_lang_selection")
def _(spark, d):
    return _fractions(tables.pages_flat(spark, d), Task("lang", "page_id", ("url", "title", "host", "tld", "body", "html")))


@query("pages_host_selection")
def _(spark, d):
    return _fractions(tables.pages_flat(spark, d), Task("host", "page_id", ("url", "tld", "lang")))


@query("documents_lang_selection")
def _(spark, d):
    docs = tables.load(spark, d, "documents").select("doc_id", "lang", "text", "source", "n_chars")
    return _fractions(docs, Task("lang", "doc_id", ("text", "source", "n_chars")))


@query("part_selection")
def _(spark, d):
    return _fractions(tables.part_titles(spark, d), PARTS)


@query("part_dependency_negative")
def _(spark, d):
    return _fractions(tables.part_titles(spark, d), PARTS.but(candidates=("p_type", "p_size"), m=None, n=None))


@query("events_dependency_negative")
def _(spark, d):
    events = tables.load(spark, d, "events")
    return _fractions(events.select("event_id", "event_type", "props", "user_id"), Task("event_type", "event_id", ("props", "user_id"), m=None, n=None))


@query("weak_labels_selection")
def _(spark, d):
    docs = tables.load(spark, d, "documents").join(tables.load(spark, d, "labels"), "doc_id")
    return _fractions(docs.select("doc_id", F.col("quality").cast("string").alias("quality"), "text", "source"), Task("quality", "doc_id", ("text", "source")))


@query("conversation_role_selection")
def _(spark, d):
    turns = tables.load(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "role", "text", F.col("turn").cast("string").alias("turn"))
    return _fractions(turns, Task("role", "id", ("text", "turn")))


@query("wide_orders_selection")
def _(spark, d):
    return _fractions(tables.wide_orders(spark, d), Task("n_name", "row_id", tables.WIDE_CANDIDATES))


@query("mobile_selection")
def _(spark, d):
    return _fractions(tables.mobile_lines(spark, d), Task("p_brand", "row_id", ("p_title", "p_name", "p_type", "p_size", "l_quantity")))


def pq_grid(df: DataFrame, task: Task) -> DataFrame:
    """(p, q, kept): number of attributes kept in each cell of the grid; a row or column of 0 keeps all."""
    parts = []
    measured = dependency.measure_each(problem.checked(df, task).filter(F.col(task.target).isNotNull()), [task.but(q=q) for q in GRID])
    for q, (f, _) in zip(GRID, measured):
        for p in GRID:
            parts.append(f.agg(F.sum((F.col("covered") / F.col("groups") >= p).cast("long")).alias("kept")).select(F.lit(p).alias("p"), F.lit(q).alias("q"), "kept"))
    spark, n = df.sparkSession, len(task.candidates)
    for p, q in [(0.0, 0.0), *((0.0, x) for x in GRID), *((x, 0.0) for x in GRID)]:
        parts.append(spark.range(1).select(F.lit(p).alias("p"), F.lit(q).alias("q"), F.lit(n).cast("long").alias("kept")))
    return reduce(DataFrame.unionByName, parts)


@query("pq_grid_attribute_counts")
def _(spark, d):
    return pq_grid(tables.geo_customer(spark, d), SHORT_GEO.but(m=None, n=None))


@query("wide_pq_grid")
def _(spark, d):
    """Mean number of the 16 attributes kept over five seeded samples: a row for each p, a column for each q."""
    wide = tables.wide_orders(spark, d)
    runs = reduce(DataFrame.unionByName, [pq_grid(wide, Task("n_name", "row_id", tables.WIDE_CANDIDATES, seed=seed)) for seed in range(1, 6)])
    per = runs.coalesce(8).withColumn("q", F.concat(F.lit("q_"), (F.col("q") * 100).cast("int")))
    return per.groupBy("p").pivot("q", ["q_0", "q_25", "q_50", "q_75"]).agg(F.round(F.avg("kept"), 6))


@query("fd_strict")
def _(spark, d):
    geo = tables.geo_customer(spark, d)
    return dependency.fd_holds(geo, "c_phone", "n_name").withColumn("attribute", F.lit("c_phone")).unionByName(
        dependency.fd_holds(geo, "c_mktsegment", "n_name").withColumn("attribute", F.lit("c_mktsegment")))


@query("fd_violation")
def _(spark, d):
    part = tables.load(spark, d, "part")
    return dependency.fd_violation_rate(part, "p_name", "p_brand").withColumn("attribute", F.lit("p_name")).unionByName(
        dependency.fd_violation_rate(part, "p_type", "p_brand").withColumn("attribute", F.lit("p_type")))


# ------------------------------------------------------------------ similarity and retrieval
def _names(spark, d) -> DataFrame:
    return tables.load(spark, d, "nation").select("n_name").crossJoin(tables.load(spark, d, "supplier").select("s_name"))


@query("lcs_lengths")
def _(spark, d):
    return _names(spark, d).withColumn("lcs", lcs_len_expr(F.col("n_name"), F.col("s_name")).cast("int"))


@query("lcs_lengths_arrow")
def _(spark, d):
    return _names(spark, d).withColumn("lcs", lcs_len_arrow("n_name", "s_name"))


@query("lcs_strings")
def _(spark, d):
    return _names(spark, d).withColumn("common", lcs_str("n_name", "s_name"))


@query("similarity_pairs")
def _(spark, d):
    _, queries, pool, _ = supply_parts(spark, d)
    left, right = retrieval.collapse_queries(queries, ["s_name", "s_phone"]), retrieval.collapse_pool(pool, SUPPLY, ["s_name", "s_phone"])
    return compare.all_pairs(left, retrieval.spread(right), 2).select(F.col("q0").alias("q_name"), F.col("p0").alias("p_name"), "similarity", "bound")


def _topk(spark, d, k: int, **options) -> DataFrame:
    _, queries, pool, _ = supply_parts(spark, d)
    return retrieval.retrieve(queries, pool, SUPPLY, ["s_phone"], k, **options)


for _k in (1, 2, 3, 10):
    QUERIES[f"topk_diverse_k{_k}"] = lambda spark, d, k=_k: _topk(spark, d, k)


@query("topk_plain_k3")
def _(spark, d):
    return _topk(spark, d, 3, diverse=False)


@query("topk_backfill_k10")
def _(spark, d):
    """Ten examples although there are fewer regions: the best of each region first, then the best other rows."""
    _, queries, pool = _regions(spark, d)
    return retrieval.retrieve(queries, pool, REGIONS, ["s_phone"], 10, backfill=True)


@query("topk_thinned_recall")
def _(spark, d):
    """The approximate mode (at most two rows of each target value) against the exact examples."""
    _, queries, pool, _ = supply_parts(spark, d)
    exact = retrieval.retrieve(queries, pool, SUPPLY, ["s_phone"], 3)
    return retrieval.recall(retrieval.retrieve(queries, retrieval.thinned_pool(pool, SUPPLY, 2), SUPPLY, ["s_phone"], 3), exact)


@query("topk_indexed_k3")
def _(spark, d):
    _, queries, pool, _ = supply_parts(spark, d)
    return retrieval.retrieve_indexed(queries, pool, SUPPLY, ["s_phone"], 3, g=3)


@query("topk_blocks_k3")
def _(spark, d):
    _, queries, pool, _ = supply_parts(spark, d)
    return blocks.retrieve_blocks(queries, pool, SUPPLY, "s_phone", 3)


@query("geo_topk_k10")
def _(spark, d):
    """All masked customers against all others, by the planner's way."""
    queries, pool = problem.split(geo_masked(spark, d)[0], GEO)
    return retrieve_planned(queries, pool, GEO, ["c_phone"])


@query("retrieval_work")
def _(spark, d):
    queries, pool = problem.split(geo_masked(spark, d)[0], GEO)
    return blocks.work(queries, pool, GEO, "c_phone")


@query("topk_all_attributes")
def _(spark, d):
    _, queries, pool, _ = supply_parts(spark, d)
    return retrieval.retrieve(queries, pool, SUPPLY, ["s_phone", "s_name"], 3)


@query("topk_null_cells")
def _(spark, d):
    masked, _, _, _ = supply_parts(spark, d)
    queries, pool = problem.split(missingness.mask_candidates(masked, SUPPLY, ["s_phone"], 0.3), SUPPLY)
    return retrieval.retrieve(queries, pool, SUPPLY, ["s_phone", "s_name"], 3)


@query("topk_random")
def _(spark, d):
    _, queries, pool, _ = supply_parts(spark, d)
    return retrieval.retrieve_random(queries, pool, SUPPLY, 3).drop("similarity")


@query("topk_random_run")
def _(spark, d):
    _, queries, pool, _ = supply_parts(spark, d)
    return retrieval.retrieve_random(queries, pool, SUPPLY, 3, per="run").drop("similarity")


@query("topk_fixed")
def _(spark, d):
    _, queries, pool, _ = supply_parts(spark, d)
    return retrieval.retrieve_fixed(queries, pool, SUPPLY, [2, 3, 5]).drop("similarity")


@query("topk_embedding")
def _(spark, d):
    e = tables.load(spark, d, "embeddings")
    asked = hash32(F.col("vec_id"), "1") % 100 < 10
    return retrieval.retrieve_embedding(e.filter(asked), e.filter(~asked), "vec_id", "embedding", "label", 3)


@query("retrieval_hit_rate")
def _(spark, d):
    _, queries, pool, truth = supply_parts(spark, d)
    parts = [metrics.retrieval_hit_rate(retrieval.retrieve(queries, pool, SUPPLY, ["s_phone"], k), truth, "s_suppkey").withColumn("k", F.lit(k)) for k in (1, 3, 10)]
    return reduce(DataFrame.unionByName, parts)


# ------------------------------------------------------------------ prompts and imputation
def _prompts(spark, d, k: int) -> DataFrame:
    _, queries, pool, _ = supply_parts(spark, d)
    examples = retrieval.retrieve(queries, pool, SUPPLY, ["s_phone"], k) if k else None
    return prompting.build_prompts(queries, pool, examples, SUPPLY, ["s_phone"])


@query("prompts_k3")
def _(spark, d):
    return _prompts(spark, d, 3)


@query("prompts_zero_shot")
def _(spark, d):
    return _prompts(spark, d, 0)


@query("prompt_tokens")
def _(spark, d):
    return prompting.prompt_tokens(_prompts(spark, d, 3))


@query("prompt_cost")
def _(spark, d):
    return prompting.prompt_cost(_prompts(spark, d, 3), suppliers(spark, d), SUPPLY, ["s_phone"])


@query("token_reduction")
def _(spark, d):
    return prompting.token_reduction(tables.geo_customer(spark, d), GEO, ["c_phone"])


@query("scripted_completion")
def _(spark, d):
    backend = backends.ScriptedBackend(lambda prompt: ' "n_name: ' + prompt.rsplit("\n", 2)[-2].rsplit(": ", 1)[-1] + '". ')
    answers = backends.complete(_prompts(spark, d, 1), backend)
    return answers.select("query_id", backends.normalise_answer(F.col("answer"), "n_name").alias("answer"))


def _supply_answers(spark, d, backend: str, k: int = 3) -> DataFrame:
    masked, _, _, _ = supply_parts(spark, d)
    return impute(masked, SUPPLY.but(k=k), backend, attributes=["s_phone"]).answers


@query("impute_nearest_vote")
def _(spark, d):
    masked, _, _, _ = supply_parts(spark, d)
    return impute(masked, SUPPLY.but(k=3), "nearest_vote", attributes=["s_phone"]).table


@query("impute_weighted_vote")
def _(spark, d):
    return _supply_answers(spark, d, "weighted_vote")


@query("impute_pattern_vote")
def _(spark, d):
    masked, _ = geo_masked(spark, d)
    result = impute(masked, GEO, "pattern_vote")
    return result.answers


@query("impute_two_targets")
def _(spark, d):
    """Nations and regions missing in the same rows, filled one after the other by the nearest example."""
    masked, _, _, _ = supply_parts(spark, d)
    both = masked.drop("is_masked").join(_regions(spark, d)[0].select("s_suppkey", "r_name"), "s_suppkey")
    return impute_many(both, [SUPPLY.but(k=1), REGIONS.but(k=1)], backend="nearest_vote", attributes=["s_phone"])


@query("long_cell_passages")
def _(spark, d):
    """Benchmark items and documents that share a passage of 100 characters or more, with its length."""
    items, docs = tables.load(spark, d, "benchmark"), tables.load(spark, d, "documents")
    return retrieval.shared_passages(items, docs, "item_id", "doc_id").select(F.col("query_id").alias("item_id"), F.col("row_id").alias("doc_id"), "length")


@query("explain_rows")
def _(spark, d):
    masked, _, _, _ = supply_parts(spark, d)
    task = SUPPLY.but(k=3)
    return explain(masked, task, impute(masked, task, "nearest_vote", attributes=["s_phone"]))


# ------------------------------------------------------------------ baselines
@query("fill_mode")
def _(spark, d):
    return baselines.fill_mode(geo_masked(spark, d)[0], GEO)


@query("fill_mode_by_segment")
def _(spark, d):
    return baselines.fill_mode(geo_masked(spark, d)[0], GEO, ["c_mktsegment"])


def _balances(spark, d) -> DataFrame:
    c = tables.load(spark, d, "customer")
    return c.withColumn("c_acctbal", F.when(hash32(F.col("c_custkey"), "1") % 100 >= 10, F.col("c_acctbal")))


@query("fill_mean")
def _(spark, d):
    return baselines.fill_mean(_balances(spark, d), "c_acctbal", "c_custkey")


@query("fill_median")
def _(spark, d):
    return baselines.fill_median(_balances(spark, d), "c_acctbal", "c_custkey")


@query("neighbour_object_sim")
def _(spark, d):
    return baselines.neighbour_object_sim(geo_masked(spark, d)[0], GEO)


@query("neighbour_ensemble")
def _(spark, d):
    return baselines.neighbour_ensemble(geo_masked(spark, d)[0], GEO, subsets=[["c_phone"], ["r_name", "c_phone"], ["c_name", "c_phone"]])


@query("cluster_fill")
def _(spark, d):
    return baselines.cluster_fill(geo_masked(spark, d)[0], GEO.but(candidates=("c_phone", "r_name", "c_mktsegment")))


@query("cluster_fill_nearest")
def _(spark, d):
    return baselines.cluster_fill(geo_masked(spark, d)[0], GEO.but(candidates=("c_phone", "r_name", "c_mktsegment")), how="nearest")


@query("relational_regression")
def _(spark, d):
    tables.shared_folder(spark, "regression")  # rounds are checkpointed
    return baselines.relational_regression(geo_masked(spark, d)[0], GEO.but(candidates=("r_name", "c_mktsegment", "c_phone")))


@query("few_label_corrector")
def _(spark, d):
    return baselines.few_label_corrector(geo_masked(spark, d)[0], GEO)


@query("probabilistic_repair")
def _(spark, d):
    return baselines.probabilistic_repair(geo_masked(spark, d)[0], GEO.but(candidates=("r_name", "c_mktsegment")))


@query("finetuned_lm_multi")
def _(spark, d):
    return baselines.finetuned_lm(geo_masked(spark, d)[0], GEO)


@query("finetuned_lm_binary")
def _(spark, d):
    masked, _, _, _ = supply_parts(spark, d)
    return baselines.finetuned_lm(masked, SUPPLY, "binary")


@query("allattr_prompt")
def _(spark, d):
    masked, _, _, _ = supply_parts(spark, d)
    return baselines.allattr_prompt(masked, SUPPLY.but(k=3), examples="random_run").answers


# ------------------------------------------------------------------ measures and workloads
@query("exact_match")
def _(spark, d):
    masked, _, _, truth = supply_parts(spark, d)
    answers = impute(masked, SUPPLY.but(k=3), "nearest_vote", attributes=["s_phone"]).answers
    return metrics.exact_match(metrics.judged(answers, truth, "s_suppkey"))


@query("rouge1")
def _(spark, d):
    """Long answers: each benchmark item judged by the item before it."""
    items = tables.load(spark, d, "benchmark").select(F.col("item_id").alias("query_id"), F.col("text").alias("truth"))
    before = items.select((F.col("query_id") + 1).alias("query_id"), F.col("truth").alias("answer"))
    return metrics.rouge1(items.join(before, "query_id", "left"))


def _geo_right(spark, d, rate: float = 0.1, seed: int = 1) -> DataFrame:
    """(query_id, truth, answer) of the nearest example's vote on c_phone."""
    masked, truth = geo_masked(spark, d, rate, seed)
    queries, pool = problem.split(masked, GEO)
    return metrics.judged(backends.nearest_vote(retrieve_planned(queries, pool, GEO.but(k=1), ["c_phone"])), truth, "c_custkey")


@query("gain_table")
def _(spark, d):
    """Exact match of the random and the diverse-similar examples and the gain, for k = 3 and 10 (weighted vote)."""
    per = arms(spark, d).groupBy("k").pivot("arm", ["selected_random", "selected_diverse"]).agg(F.round(F.avg("exact"), 6))
    return per.withColumn("gain", F.when(F.col("selected_random") > 0, metrics.gain(F.col("selected_random"), F.col("selected_diverse"))))


@query("mean_std")
def _(spark, d):
    """Mean and deviation of the exact match over five seeded runs."""
    runs = [metrics.exact_match(_geo_right(spark, d, seed=seed)).select(F.lit(seed).alias("seed"), "exact_match") for seed in range(1, 6)]
    return metrics.mean_std(reduce(DataFrame.unionByName, runs).withColumn("method", F.lit("nearest_vote")), ["method"], "exact_match")


@query("counters")
def _(spark, d):
    masked, _ = geo_masked(spark, d)
    return metrics.counters(masked, problem.split(masked, GEO)[1], ["c_phone", "c_name"], ["c_phone"])


def arms(spark, d, ks=(3, 10), seeds=(1,)) -> DataFrame:
    """(arm, k, seed, exact): one row per masked cell of each ablation arm, decided by the weighted vote."""
    parts = []
    for seed in seeds:
        masked, _, _, truth = supply_parts(spark, d, seed)
        for k in ks:
            task = SUPPLY.but(k=k, seed=seed)
            for arm, names, examples in (("all_random", ["s_name", "s_phone"], "random_run"), ("selected_random", ["s_phone"], "random_run"),
                                         ("all_diverse", ["s_name", "s_phone"], "diverse"), ("selected_diverse", ["s_phone"], "diverse")):
                answers = impute(masked, task, "weighted_vote", examples=examples, attributes=names).answers
                pairs = metrics.judged(answers, truth, "s_suppkey")
                parts.append(pairs.select(F.lit(arm).alias("arm"), F.lit(k).alias("k"), F.lit(seed).alias("seed"),
                                          F.coalesce((F.col("answer") == F.col("truth")).cast("int"), F.lit(0)).alias("exact")))
    return reduce(DataFrame.unionByName, parts)


@query("ablation_cube")
def _(spark, d):
    return arms(spark, d, ks=(3,)).cube("arm", "k").agg(F.count("*").alias("cells"), F.round(F.avg("exact"), 6).alias("exact_match"))


@query("missing_rate_sweep")
def _(spark, d):
    """Exact match of the method's nearest vote at 10 to 50 % missing."""
    parts = [metrics.exact_match(_geo_right(spark, d, rate / 100)).select(F.lit(rate).alias("rate"), "cells", "exact_match") for rate in (10, 20, 30, 40, 50)]
    return reduce(DataFrame.unionByName, parts)


@query("small_model_comparison")
def _(spark, d):
    """All attributes with random examples against the method, each with a weak and a strong evidence backend."""
    masked, truth = geo_masked(spark, d)
    arms_of = (("all attributes, random", "weak", dict(backend="nearest_vote", examples="random_run", attributes=list(GEO.candidates))),
               ("all attributes, random", "strong", dict(backend="weighted_vote", examples="random_run", attributes=list(GEO.candidates))),
               ("localized", "weak", dict(backend="nearest_vote")), ("localized", "strong", dict(backend="pattern_vote")))
    parts = [metrics.exact_match(metrics.judged(impute(masked, GEO, **options).answers, truth, "c_custkey")).select(
        F.lit(method).alias("method"), F.lit(backend).alias("backend"), "cells", "exact_match") for method, backend, options in arms_of]
    return reduce(DataFrame.unionByName, parts)


@query("rouge1_answers")
def _(spark, d):
    return metrics.rouge1(_geo_right(spark, d))


@query("synthetic_runtime_shape")
def _(spark, d):
    parts = []
    for m, n, size in ((10, 10, 10), (10, 10, 100), (20, 10, 100), (10, 20, 100)):
        task = Task("target", "row_id", ("value",), p=0.5, q=0.5, m=m, n=n)
        parts.append(_fractions(tables.lengths(spark, m, n, size), task).select(F.lit(m).alias("m"), F.lit(n).alias("n"), F.lit(size).alias("l"), "covered", "groups", "holds"))
    return reduce(DataFrame.unionByName, parts)


# ------------------------------------------------------------------ summaries that users of the tables need
@query("order_ranks")
def _(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    per_status = Window.partitionBy("o_custkey").orderBy("o_orderstatus")
    return tables.load(spark, d, "orders").select("o_orderkey", "o_custkey", F.row_number().over(w).alias("place"), F.ntile(4).over(w).alias("quarter"),
                                                  F.rank().over(per_status).alias("status_rank"), F.dense_rank().over(per_status).alias("status_dense_rank"))


@query("order_windows")
def _(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    so_far = w.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return tables.load(spark, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey").over(w).alias("after"),
                                                  F.first_value("o_orderkey").over(w).alias("first"), F.round(F.sum("o_totalprice").over(so_far), 2).alias("running"))


@query("segment_rollup")
def _(spark, d):
    return tables.geo_customer(spark, d).rollup("r_name", "c_mktsegment").agg(F.count("*").alias("customers"))


@query("segment_grouping_sets")
def _(spark, d):
    return spark.sql("""SELECT r_name, c_mktsegment, count(*) AS customers, count(DISTINCT n_name) AS nations FROM {geo}
                        GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())""", geo=tables.geo_customer(spark, d))


@query("distinct_values")
def _(spark, d):
    """Exact numbers of distinct values, and whether the sketches with a deviation of 1 % come within 5 % of them."""
    geo, parts = tables.geo_customer(spark, d), []
    for c in ("c_phone", "c_name", "n_name"):
        parts.append(geo.agg(F.countDistinct(c).alias("exact"), F.approx_count_distinct(c, 0.01).alias("sketch")).select(
            F.lit(c).alias("attribute"), "exact", (F.abs(F.col("sketch") - F.col("exact")) <= 0.05 * F.col("exact")).alias("within")))
    return reduce(DataFrame.unionByName, parts)


@query("event_properties")
def _(spark, d):
    props = F.from_json("props", "map<string,long>")
    return tables.load(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("events"), F.sum(props["k"]).alias("sum_k"), F.max(F.get_json_object("props", "$.k").cast("long")).alias("max_k"))


@query("pool_set_operations")
def _(spark, d):
    """Phone codes' texts of two samples: in both, and in the first only."""
    geo = tables.geo_customer(spark, d)
    a, b = (sampling.sample_groups(geo, GEO.but(seed=seed)).select("n_name", "c_mktsegment") for seed in (1, 2))
    return a.intersect(b).withColumn("part", F.lit("both")).unionByName(a.distinct().exceptAll(b.distinct()).withColumn("part", F.lit("first")))


@query("stream_window_counts")
def _(spark, d):
    events = tables.load(spark, d, "events")
    return stream.window_counts(events, "ts", "event_type", "1 day").withColumn("window_start", F.date_format("window_start", "yyyy-MM-dd"))


@query("stream_session_counts")
def _(spark, d):
    out = stream.session_counts(tables.load(spark, d, "events"), "ts", "user_id")
    return out.select("user_id", F.date_format("session_start", "yyyy-MM-dd HH:mm:ss").alias("session_start"), "events")


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Flagship: geo_customer with 10 % of its nations missing, filled end to end, with the truth beside."""
    masked, truth = geo_masked(spark, sf_dir)
    result = impute(masked, GEO, "pattern_vote")
    return metrics.judged(result.answers, truth, "c_custkey").withColumn("right", F.col("answer") == F.col("truth"))


QUERIES["geo_end_to_end"] = entry
