"""Worked examples, properties and differential tests of the imputation engine."""

import json
import random
import threading
from http.server import BaseHTTPRequestHandler, ThreadingHTTPServer

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from textimpute.functions import lcs
from textimpute.functions.automaton import SuffixAutomaton, lcs_length, lcs_string
from textimpute.operators import backends, baselines, dependency, impute, metrics, missingness, patterns, problem, prompting, retrieval, sampling
from textimpute.operators.problem import Task
from textimpute.plans.planner import choose_retrieval
from textimpute.sources import tables

PHONES = [("t1", "212/355-7048", "New York"), ("t2", "702/648-5520", "Las Vegas"), ("t3", "212/860-0254", "New York"), ("t4", "702/364-5584", "Las Vegas"),
          ("t5", "(702-) 385 446", "Las Vegas"), ("t6", "646/478-8855", "New York")]
QUERY = "702-796-1133"
TASK = Task("city", "id", ("phone",), m=None, n=None)


def frame(spark, rows, schema="id string, phone string, city string"):
    return spark.createDataFrame(rows, schema)


# ---------------------------------------------------------------- strings
def slow_lcs(a, b):
    return max((n for n in range(len(a) + 1) for i in range(len(a) - n + 1) if a[i:i + n] in b), default=0)


@settings(max_examples=150, deadline=None)
@given(st.text("abé😀 ", max_size=14), st.text("abé😀 ", max_size=14))
def test_automaton_lcs(a, b):
    assert lcs_length(a, b) == slow_lcs(a, b)
    common = lcs_string(a, b)
    assert len(common) == slow_lcs(a, b) and common in a and common in b
    assert a.find(common) == min((a.find(a[i:i + len(common)]) for i in range(len(a) - len(common) + 1) if a[i:i + len(common)] in b), default=0)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.text("abc", max_size=8), min_size=1, max_size=5), st.integers(1, 5))
def test_frequent_and_maximal_substrings(texts, least):
    every = {t[i:j] for t in texts for i in range(len(t)) for j in range(i + 1, len(t) + 1)}
    frequent = {s: n for s in every if (n := sum(s in t for t in texts)) >= least}
    automaton = SuffixAutomaton(*texts)
    assert dict(automaton.frequent(least)) == frequent
    assert dict(automaton.maximal(least)) == {s: n for s, n in frequent.items() if not any(s != o and s in o for o in frequent)}


def test_lcs_expression_equals_automaton(spark):
    rng = random.Random(1)
    cells = [None, "", "x", "é😀é", *("".join(rng.choice("abc1é") for _ in range(rng.randint(0, 40))) for _ in range(40))]
    df = frame(spark, [(a, b) for a in cells for b in cells], "a string, b string")
    rows = df.select("a", "b", lcs.lcs_len_expr(F.col("a"), F.col("b")).alias("x"), lcs.lcs_len_arrow("a", "b").alias("y")).collect()
    for r in rows:
        want = slow_lcs(r["a"], r["b"]) if r["a"] is not None and r["b"] is not None else 0
        assert r["x"] == want and (r["y"] or 0) == want


def test_sql_names(spark):
    lcs.register(spark)
    row = spark.sql("SELECT lcs_len('702-796', '702/64') AS a, lcs_str('xabcy', 'zabc') AS b, lcs_sim('abcd', 'abxx') AS c, rouge1_f1('alpha', 'alpha beta') AS d").first()
    assert (row["a"], row["b"], row["c"], round(row["d"], 3)) == (3, "abc", 0.5, 0.667)
    assert {r["pattern"] for r in spark.sql("SELECT * FROM shared_substrings('abcXdef', 'defYabc', 3)").collect()} == {"abc", "def"}
    assert [(r["pattern"], r["support"]) for r in spark.sql("SELECT * FROM group_patterns(array('702-1', '702/2', 'x'), double(0.6))").collect()] == [("702", 2)]
    frame(spark, PHONES).createOrReplaceTempView("phones")
    got = {r["city"]: r["p"] for r in spark.sql("SELECT city, common_substring(phone, double(1.0)) AS p FROM phones GROUP BY city").collect()}
    assert got["Las Vegas"] == "702"


# ---------------------------------------------------------------- worked similarity example
def test_phone_ranking(spark):
    queries, pool = frame(spark, [("q", QUERY, None)]), frame(spark, PHONES)
    plain = {r["example_id"]: round(r["similarity"], 3) for r in retrieval.retrieve(queries, pool, TASK, ["phone"], 6, diverse=False).collect()}
    assert plain == {"t1": 0.167, "t2": 0.25, "t3": 0.167, "t4": 0.25, "t5": 0.286, "t6": 0.083}
    for k, want in ((1, ["t5"]), (2, ["t5", "t1"])):
        rows = retrieval.retrieve(queries, pool, TASK, ["phone"], k).orderBy("rank").collect()
        assert [r["example_id"] for r in rows] == want


def test_null_cells_lower_similarity(spark):
    task = Task("t", "id", ("a", "b"))
    queries = spark.createDataFrame([(1, "xyz", None, None)], "id long, a string, b string, t string")
    pool = spark.createDataFrame([(2, "xyz", "q", "v")], "id long, a string, b string, t string")
    assert retrieval.retrieve(queries, pool, task, ["a", "b"], 3).first()["similarity"] == 0.5


@pytest.mark.parametrize("g", [2, 3, 5])
def test_indexed_retrieval_is_exact(spark, g):
    rng = random.Random(g)
    word = lambda: "".join(rng.choice("0123456789-") for _ in range(rng.randint(0, 14)))
    task = Task("t", "id", ("a", "b"))
    pool = spark.createDataFrame([(i, word(), rng.choice([None, word()]), f"v{rng.randint(0, 8)}") for i in range(150)], "id long, a string, b string, t string")
    queries = spark.createDataFrame([(i, word(), word(), None) for i in range(1000, 1030)], "id long, a string, b string, t string")
    key = lambda df: sorted((r["query_id"], r["rank"], r["example_id"], r["target_value"], r["similarity"]) for r in df.collect())
    want = retrieval.retrieve(queries, pool, task, ["a", "b"], 3)
    assert key(retrieval.retrieve_indexed(queries, pool, task, ["a", "b"], 3, g=g)) == key(want)
    assert all(0 <= r["similarity"] <= 1 for r in want.collect())
    marked = retrieval.retrieve_indexed(queries, pool, task, ["a", "b"], 3, g=g, report=True)
    assert {r["certified"] for r in marked.collect()} <= {True, False} and marked.count() == want.count()


def test_planner_switches_by_cost(spark):
    df = frame(spark, PHONES)
    assert choose_retrieval(df, df, ["phone"]).way == "nested" and choose_retrieval(df, df, ["phone"], budget=10).way == "indexed"


# ---------------------------------------------------------------- sampling, patterns, dependencies
def test_shortfall_quota():
    assert sampling.shortfall_quota({10: 2, 9: 2, 4: 1, 1: 1}, 4, 10) == {10: 2, 9: 2, 1: 1}
    assert sampling.shortfall_quota({10: 50}, 4, 10) == {10: 4}
    assert sampling.shortfall_quota({}, 4, 10) == {}


def test_threshold_p(spark):
    codes = ["11a", "22b", "33c", "44d"]
    rows = [(f"{c}{i}", f"{c}-{i}", c) for c in codes for i in range(3)] + [("x1", "zz", "none"), ("x2", "yy", "none"), ("x3", "ww", "none")]
    long = patterns.unpivot_sample(frame(spark, rows), TASK)
    found = patterns.unique_patterns(patterns.mine_frequent(long, 1.0))
    for p, holds in ((0.8, True), (0.81, False)):
        row = dependency.evaluate(found, long, p).first()
        assert (row["covered"], row["groups"], row["holds"]) == (4, 5, holds)


def test_formats_share_the_code(spark):
    rows = [("1", "702-123-4567", "LV"), ("2", "(702-) 999 111", "LV"), ("3", "702/555-0000", "LV"), ("4", "212-000-1111", "NY"), ("5", "212/444-5555", "NY")]
    long = patterns.unpivot_sample(frame(spark, rows), TASK)
    found = {(r["target_value"], r["pattern"]) for r in patterns.unique_patterns(patterns.mine_frequent(long, 1.0)).collect()}
    assert ("LV", "702") in found


def test_miners_agree_and_filters_commute(spark):
    rng = random.Random(3)
    rows = [(str(i), rng.choice([None, "".join(rng.choice("ab1") for _ in range(rng.randint(0, 7)))]), f"g{i % 4}") for i in range(40)]
    long = patterns.unpivot_sample(frame(spark, rows), TASK)
    key = lambda df: sorted((r["target_value"], r["pattern"], r["support"]) for r in df.collect())
    for q in (0.25, 0.5, 0.75):
        every = patterns.mine_frequent(long, q, "all")
        assert key(every) == key(patterns.mine_frequent_native(long, q))
        maximal = patterns.mine_frequent(long, q)
        assert key(patterns.drop_contained(patterns.unique_patterns(every))) == key(patterns.unique_patterns(maximal))
        pairwise = {x[:2] for x in key(patterns.mine_frequent(long, q, "pairwise"))}
        assert pairwise <= {x[:2] for x in key(every)}
    assert key(patterns.mine_frequent(long, 0.5, "longest"))


def test_holds_is_antitone_in_p_and_empty_selection_falls_back(spark):
    rows = [(str(i), f"{'ab'[i % 2]}{i}", f"g{i % 2}") for i in range(20)] + [(f"z{i}", "q", f"h{i}") for i in range(2)]
    df = frame(spark, rows)
    held = [dependency.select_attributes(df, TASK.but(p=p, q=0.9)).evidence.first()["holds"] for p in (0.25, 0.5, 0.75, 1.0)]
    assert held == sorted(held, reverse=True)
    strict = TASK.but(p=1.0, q=1.0)
    assert dependency.select_attributes(df, strict).attributes == ["phone"] and "all" in dependency.select_attributes(df, strict).note
    with pytest.raises(ValueError):
        dependency.select_attributes(df, strict, on_empty="error")
    assert dependency.select_attributes(df, TASK.but(p=0)).attributes == ["phone"]


# ---------------------------------------------------------------- filling
def test_fill_touches_only_missing_cells(spark):
    df = frame(spark, [*PHONES, ("q", QUERY, None), ("n", None, None)])
    result = impute.impute(df, TASK.but(k=2), "nearest_vote", attributes=["phone"])
    out = {r["id"]: r for r in result.table.collect()}
    assert out["q"]["city"] == "Las Vegas" and out["q"]["city_imputed"] and not out["t1"]["city_imputed"]
    assert result.table.filter("not city_imputed").drop("city_imputed").exceptAll(df).count() == 0
    assert impute.explain(df, TASK, result).filter("query_id = 'q' and rank = 1").first()["common"] == "702-"


def test_prompts_and_backends(spark, tmp_path):
    df = frame(spark, [*PHONES, ("q", QUERY, None), ("r", QUERY, None)])
    asked = []
    backend = backends.ScriptedBackend(lambda p: "city: 'Las Vegas'.")
    log = str(tmp_path / "log")
    for _ in range(2):
        result = impute.impute(df, TASK.but(k=2), backend, attributes=["phone"], log=log)
        assert {(r["query_id"], r["answer"]) for r in result.answers.collect()} == {("q", "Las Vegas"), ("r", "Las Vegas")}
    assert spark.read.parquet(log).count() == 1  # equal prompts are asked once, and not again
    prompt = result.prompts.first()["prompt"]
    assert prompt.split("\n")[1] == "phone: (702-) 385 446; city: Las Vegas" and prompt.endswith(f"phone: {QUERY}; city: ")
    zero = prompting.build_prompts(*reversed(problem.split(df, TASK)[::-1]), None, TASK, ["phone"])
    assert {r["k"] for r in zero.collect()} == {0} and not asked


def prompts_of(spark, n):
    return spark.range(n).select(F.col("id").alias("query_id"), F.concat(F.lit("h"), F.col("id") % 6).alias("prompt_hash"), F.concat(F.lit("what is "), F.col("id") % 6).alias("prompt"))


def test_hosted_backend_asks_each_prompt_once_and_again_after_an_error(spark, tmp_path):
    seen, failed = [], set()

    class Stub(BaseHTTPRequestHandler):
        def do_POST(self):
            asked = json.loads(self.rfile.read(int(self.headers["Content-Length"])))
            prompt = asked["messages"][0]["content"]
            if prompt.endswith("3") and prompt not in failed:
                failed.add(prompt)
                return self.send_error(503)
            seen.append((prompt, asked["model"], self.headers["Authorization"]))
            body = json.dumps({"choices": [{"message": {"content": prompt[-1] * 2}}]}).encode()
            self.send_response(200)
            self.end_headers()
            self.wfile.write(body)

        def log_message(self, *_):
            pass

    server = ThreadingHTTPServer(("127.0.0.1", 0), Stub)
    threading.Thread(target=server.serve_forever, daemon=True).start()
    try:
        backend = backends.HttpChatBackend(f"http://127.0.0.1:{server.server_port}/", "stub", key="k", per_second=1000)
        answers = backends.complete(prompts_of(spark, 12), backend, wave=2)
        for _ in range(2):  # every action reads what was written
            assert {(r["query_id"], r["answer"]) for r in answers.collect()} == {(i, str(i % 6) * 2) for i in range(12)}
        assert sorted(seen) == [(f"what is {i}", "stub", "Bearer k") for i in range(6)] and failed == {"what is 3"}
    finally:
        server.shutdown()


def test_failed_waves_keep_the_answers_before_them(spark, tmp_path):
    log, marks = str(tmp_path / "log"), tmp_path / "asked"
    marks.mkdir()

    def answer(prompt, broken):
        if broken and prompt.endswith("5"):
            raise ValueError("no answer")
        with open(marks / prompt[-1], "a") as f:
            f.write("x")
        return prompt[-1]

    with pytest.raises(Exception, match="no answer"):
        backends.complete(prompts_of(spark, 6), backends.ScriptedBackend(lambda p: answer(p, True)), log, wave=1)
    kept = {r["prompt_hash"] for r in spark.read.schema("prompt_hash string, answer string").parquet(log).collect()}
    out = backends.complete(prompts_of(spark, 12), backends.ScriptedBackend(lambda p: answer(p, False)), log, wave=1)
    assert {(r["query_id"], r["answer"]) for r in out.collect()} == {(i, str(i % 6)) for i in range(12)}
    assert all((marks / h[-1]).read_text() == "x" for h in kept)  # an answer that was written is not asked for again


def test_local_model_is_loaded_in_the_worker(spark):
    backend = backends.LocalModelBackend(lambda: lambda prompts: [p.upper() for p in prompts])
    out = backends.complete(prompts_of(spark, 3), backend)
    assert {r["answer"] for r in out.collect()} == {"WHAT IS 0", "WHAT IS 1", "WHAT IS 2"}
    assert backends.complete(prompts_of(spark, 3).filter("false"), backend).count() == 0


def test_random_examples_come_from_all_decks(spark):
    rows = [(str(i), f"{i:04d}", f"v{i}" if i % 2 else None) for i in range(600)]
    queries, pool = problem.split(frame(spark, rows), TASK)
    out = retrieval.retrieve_random(queries, pool, TASK, 4, deck=20).collect()
    by_query = {}
    for r in out:
        by_query.setdefault(r["query_id"], []).append((r["rank"], r["example_id"], r["target_value"]))
    assert len(by_query) == 300 and all(sorted(x[0] for x in v) == [1, 2, 3, 4] and len({x[1] for x in v}) == 4 for v in by_query.values())
    assert all(x[2] == f"v{x[1]}" for v in by_query.values() for x in v) and len({x[1] for v in by_query.values() for x in v}) > 250
    again = retrieval.retrieve_random(queries.repartition(3), pool.repartition(5), TASK, 4, deck=20).collect()
    assert sorted(map(tuple, out)) == sorted(map(tuple, again))


def test_backfill_and_thinned_pool(spark):
    df = frame(spark, [*PHONES, ("q", QUERY, None)])
    queries, pool = problem.split(df, TASK)
    plain = retrieval.retrieve(queries, pool, TASK, ["phone"], 4).collect()
    filled = sorted(retrieval.retrieve(queries, pool, TASK, ["phone"], 4, backfill=True).collect(), key=lambda r: r["rank"])
    assert len(plain) == 2 and [r["rank"] for r in filled] == [1, 2, 3, 4]
    assert {tuple(r) for r in plain} == {tuple(r) for r in filled[:2]}
    assert filled[2]["similarity"] >= filled[3]["similarity"] and len({r["example_id"] for r in filled}) == 4
    thin = retrieval.thinned_pool(pool, TASK, 1)
    assert {r["city"] for r in thin.collect()} == {"New York", "Las Vegas"} and thin.count() == 2
    exact = retrieval.retrieve(queries, pool, TASK, ["phone"], 2)
    assert retrieval.recall(exact, exact).first()["recall"] == 1.0
    with pytest.raises(ValueError):
        retrieval.guarded(10, 10, 99)


def test_shared_passages_equal_brute_force(spark):
    rng = random.Random(3)
    word = lambda n: "".join(rng.choice("abc") for _ in range(n))
    items = [(i, word(rng.randrange(0, 60))) for i in range(12)] + [(12, None)]
    docs = [(i, word(30) + (items[i % 12][1] or "")[: rng.randrange(0, 50)] + word(rng.randrange(0, 40))) for i in range(40)] + [(40, None), (41, "")]
    want = {(i, d, lcs_length(a, b)) for i, a in items for d, b in docs if a and b and lcs_length(a, b) >= 13}
    schema = "id long, text string"
    for most in (0, 1000):
        got = retrieval.shared_passages(spark.createDataFrame(items, schema), spark.createDataFrame(docs, schema), "id", "id", least=13, most_blocks=most)
        assert {tuple(r) for r in got.collect()} == want and want


def test_repeated_row_ids_do_not_multiply_rows(spark):
    df = frame(spark, [*PHONES, ("q", QUERY, None), ("q", QUERY, None)])
    assert impute.impute(df, TASK.but(k=1), "nearest_vote", attributes=["phone"]).table.count() == df.count()


def test_thresholds_measured_on_one_sample(spark, sf):
    geo = problem.checked(tables.geo_customer(spark, sf), Task("n_name", "c_custkey", ("c_phone", "c_mktsegment")))
    task = Task("n_name", "c_custkey", ("c_phone", "c_mktsegment"), m=5, n=6)
    for sized in (task, task.but(m=None, n=None)):
        each = dependency.measure_each(geo, [sized.but(q=q) for q in (0.25, 0.75)])
        for q, (evidence, _) in zip((0.25, 0.75), each):
            assert sorted(map(tuple, evidence.collect())) == sorted(map(tuple, dependency.measure(geo, sized.but(q=q))[0].collect()))
    with pytest.raises(ValueError):
        dependency.measure_each(geo, [task, task.but(m=6)])


def test_votes_and_arms(spark):
    df = frame(spark, [*PHONES, ("q", QUERY, None)])
    for name in ("nearest_vote", "weighted_vote", "pattern_vote"):
        assert [r["answer"] for r in impute.impute(df, TASK.but(k=3, p=0.5, q=0.6), name).answers.collect()] == ["Las Vegas"]
    for examples in ("random", "random_run", "plain", ["t1", "t2"]):
        assert impute.impute(df, TASK.but(k=2), "weighted_vote", examples=examples, attributes=["phone"]).answers.count() == 1


def test_leakage(spark, sf):
    geo = tables.geo_customer(spark, sf)
    masked, truth = missingness.mask_by(geo, Task("n_name", "c_custkey", ("c_phone",)), "c_mktsegment", 0.5)
    assert set(masked.columns) - set(geo.columns) == {"is_masked"} and set(truth.columns) == {"c_custkey", "truth"}
    assert masked.filter("is_masked").select("c_mktsegment").distinct().intersect(masked.filter("not is_masked").select("c_mktsegment").distinct()).count() == 0


def test_baselines_answer_every_query(spark):
    rows = [(str(i), f"{['702', '212', '646'][i % 3]}-{i:04d}", ["LV", "NY", "BX"][i % 3] if i % 7 else None) for i in range(60)]
    df = frame(spark, rows)
    task = TASK.but(k=3)
    missing = df.filter("city is null").count()
    for fill in (baselines.fill_mode, baselines.neighbour_ensemble, lambda d, t: baselines.cluster_fill(d, t, clusters=3), lambda d, t: baselines.cluster_fill(d, t, clusters=3, how="nearest"),
                 baselines.probabilistic_repair, baselines.relational_regression, baselines.few_label_corrector, baselines.finetuned_lm):
        out = fill(df, task).collect()
        assert len(out) <= missing and all(r["answer"] in ("LV", "NY", "BX", None) for r in out)
    assert baselines.neighbour_object_sim(df, task).count() == missing
    assert {r["answer"] for r in baselines.finetuned_lm(df, task, "binary").collect()} <= {"LV", "NY", "BX"}


# ---------------------------------------------------------------- measures
def test_rouge_and_gain(spark):
    pairs = spark.createDataFrame([(1, "alpha beta", "alpha"), (2, "alpha beta", "alpha beta gamma"), (3, "x", None)], "query_id long, truth string, answer string")
    of = metrics.rouge1_of(F.col("answer"), F.col("truth"))
    got = [(round(r["precision"], 3), round(r["recall"], 3), round(r["f1"], 3)) for r in pairs.orderBy("query_id").select(*(c.alias(n) for n, c in of.items())).collect()]
    assert got == [(1.0, 0.5, 0.667), (0.667, 1.0, 0.8), (0.0, 0.0, 0.0)]
    assert metrics.exact_match(pairs).first()["exact_match"] == 0
    published = [(0.747, 0.761, 1.9), (0.846, 0.958, 13.2), (0.923, 0.974, 5.5), (0.761, 0.816, 7.2), (0.128, 0.252, 96.9), (0.854, 0.964, 12.9)]
    df = spark.createDataFrame([(a, b) for a, b, _ in published], "a double, b double")
    for row, (_, _, want) in zip(df.select(metrics.gain(F.col("a"), F.col("b")).alias("g")).collect(), published):
        assert abs(row["g"] - want) <= 0.06


def test_streams_equal_batches(spark, sf, tmp_path):
    from textimpute.streaming import stream

    geo = tables.geo_customer(spark, sf).select("c_custkey", "n_name", "c_phone")
    task = Task("n_name", "c_custkey", ("c_phone",), m=None, n=None, k=3)
    masked, _ = missingness.mask_mcar(geo, task, 0.2)
    masked = masked.drop("is_masked")
    queries, pool = problem.split(masked, task)
    queries.repartition(3).write.parquet(str(tmp_path / "in"))
    reader = spark.readStream.schema(queries.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    chosen = dependency.Selection(["c_phone"])
    stream.impute_stream(reader, task, chosen, pool, str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination(120)
    got = {r["c_custkey"]: r["n_name"] for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    want = {r["query_id"]: r["answer"] for r in impute.impute(masked, task, "nearest_vote", attributes=["c_phone"]).answers.collect()}
    assert got == want
    q = stream.target_counts(spark.readStream.schema(pool.schema).parquet(str(_saved(pool, tmp_path / "pool"))), "n_name").writeStream.format("memory").queryName("counts").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination(120)
    counted = {r["target_value"]: r["rows"] for r in spark.sql("select target_value, max(rows) as rows from counts group by 1").collect()}
    assert counted == {r["n_name"]: r["count"] for r in pool.groupBy("n_name").count().collect()}


def _saved(df, path):
    df.write.parquet(str(path))
    return path


def test_deterministic_under_repartitioning(spark, sf):
    geo = tables.geo_customer(spark, sf)
    task = Task("n_name", "c_custkey", ("c_phone",), m=4, n=5)
    a, b = (sorted(r[0] for r in sampling.sample_groups(geo.repartition(n), task).select("c_custkey").collect()) for n in (1, 7))
    assert a == b


# ---------------------------------------------------------------- blocks and uniqueness
def test_blocks_equal_the_nested_comparison(spark):
    import random

    from textimpute.operators.blocks import Block, retrieve_blocks
    from textimpute.operators.problem import Task, split
    from textimpute.operators.retrieval import retrieve

    rng = random.Random(5)
    cell = lambda: rng.choice([None, "", "".join(rng.choice("abc-") for _ in range(rng.randint(1, 9)))])
    df = spark.createDataFrame([(k, None if k % 5 == 0 else f"t{rng.randint(0, 6)}", cell()) for k in range(150)], "id long, t string, c string")
    task = Task("t", "id", ("c",), k=4)
    queries, pool = split(df, task)
    want = sorted(map(str, retrieve(queries, pool, task, ["c"]).collect()))
    for chars, size in ((100_000, 16_000_000), (20, 300)):
        assert sorted(map(str, retrieve_blocks(queries, pool, task, "c", block_chars=chars, slice_chars=size).collect())) == want
    block = Block(["abab", "xabx", None], [9, 4, 2])
    assert block.best("ab") == (0.5, 4) and block.best("zz") == (0.0, 2) and block.best(None) == (0.0, 2)


def test_uniqueness_in_rows_for_every_mode(spark):
    import random

    from textimpute.operators.patterns import MODES, mine_frequent, unique_for, unique_in_rows

    rng = random.Random(6)
    rows = [("a", "A", "1", "ab1"), ("a", "A", "2", "ab2"), ("a", "B", "3", "ab-longest"), ("a", "B", "4", "longest=ab")]
    rows += [("b", f"G{k % 4}", str(10 + k), "".join(rng.choice("xyz") for _ in range(rng.randint(2, 7)))) for k in range(24)]
    long = spark.createDataFrame(rows, "attribute string, target_value string, row_id string, value string")
    groups = {}
    for a, t, _, v in rows:
        groups.setdefault((a, t), []).append(v)

    def frequent_in(a, p, q):
        return [t for (b, t), v in groups.items() if a == b and sum(p in x for x in v) >= q * len(v)]

    for mode in MODES:
        for q, limit in ((1.0, None), (0.5, None), (0.5, 2)):
            mined = mine_frequent(long, q, mode, max_len=limit)
            kept = (unique_for(mined, long, q, mode) if limit is None else unique_in_rows(mined, long, q)).collect()
            want = {(r["attribute"], r["target_value"], r["pattern"]) for r in mined.collect() if frequent_in(r["attribute"], r["pattern"], q) == [r["target_value"]]}
            assert {(r["attribute"], r["target_value"], r["pattern"]) for r in kept} == want
            assert not any(r["pattern"] == "ab" for r in kept)


def test_driver_and_cluster_mine_alike(spark):
    import random

    from textimpute.operators.dependency import measure
    from textimpute.operators.problem import Task

    rng = random.Random(7)
    df = spark.createDataFrame([(k, f"t{k % 5}", f"code{k % 5}-{rng.randint(0, 99)}", rng.choice(["red", "blue", None])) for k in range(200)], "id long, t string, c string, d string")
    for mode in ("maximal", "longest", "pairwise"):
        task = Task("t", "id", ("c", "d"), m=4, n=6)
        near, far = measure(df, task, mode), measure(df, task, mode, local_chars=0)
        for a, b in zip(near, far):
            assert sorted(map(str, a.collect())) == sorted(map(str, b.collect()))
