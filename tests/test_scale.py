"""What keeps queries within their limits on larger tables: each way against brute force, and the plans."""

import random
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pytest

from textimpute.functions.automaton import lcs_length, lcs_string
from textimpute.functions.lcstable import LcsTable
from textimpute.operators import compare, retrieval
from textimpute.operators.problem import Task

TASK = Task("city", "id", ("a", "b"))
SCHEMA = "id long, city string, a string, b string"


def random_rows(seed: int, n: int, first: int = 0):
    r = random.Random(seed)
    cell = lambda: r.choice([None, "", "".join(r.choice("abc\U0001f600") for _ in range(r.randint(1, 9)))])
    return [(first + i, r.choice("uvwxyz"), cell(), cell()) for i in range(n)]


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_table_of_texts_equals_automata():
    r = random.Random(3)
    texts = ["", "a", "abab", "x" * 300, "né\U0001f600e", *("".join(r.choice("abcd") for _ in range(r.randint(1, 40))) for _ in range(60))]
    table = LcsTable(texts)
    for text in [*texts, "zz", "x" * 254, "a" * 260 + "bcd"]:
        n, end = table.longest(text)
        assert table.lengths(text).tolist() == n.tolist() == [lcs_length(text, t) for t in texts]
        assert [text[e - k:e] for k, e in zip(n, end)] == [lcs_string(text, t) for t in texts]


def test_rounding_is_half_up_of_the_decimal():
    values = [0.0, 1.0, 1 / 1024, 3 / 1024, 1 / 3, 2 / 3, 0.123456789499999, *(i / 2048 for i in range(100))]
    want = [int(Decimal(repr(v)).quantize(Decimal("1e-9"), ROUND_HALF_UP).scaleb(9)) for v in values]
    assert compare.rounded(np.array(values)).tolist() == want


@pytest.mark.parametrize("options", [dict(), dict(diverse=False), dict(backfill=True)])
def test_retrieval_by_blocks_equals_brute_force(spark, options):
    asked, known = random_rows(1, 12, 1000), random_rows(2, 60)
    queries, pool = spark.createDataFrame([(i, None, a, b) for i, _, a, b in asked], SCHEMA), spark.createDataFrame(known, SCHEMA)
    similar = lambda x, y: 0.0 if not x or not y else lcs_length(x, y) / max(len(x), len(y))
    for k in (2, 9):
        want = []
        for i, _, a, b in asked:
            best = sorted((-round((similar(a, p[2]) + similar(b, p[3])) / 2, 9), p[0], p[1]) for p in known)
            seen, marked = set(), []
            for s, e, city in best:
                marked.append((city in seen, s, e, city))
                seen.add(city)
            if options.get("diverse", True):
                marked = sorted(marked) if options.get("backfill") else [m for m in marked if not m[0]]
            want += [(i, n + 1, e, city, -s) for n, (_, s, e, city) in enumerate(marked[:k])]
        got = retrieval.retrieve(queries, pool, TASK, ["a", "b"], k, **options)
        assert sorted(map(tuple, got.collect())) == want
        assert "NestedLoop" not in plan_of(got) and "Cartesian" not in plan_of(got)


@pytest.mark.parametrize("rows", [1, 5, 100])
def test_candidates_do_not_depend_on_the_cut(spark, rows):
    queries, pool = spark.createDataFrame(random_rows(4, 9, 1000), SCHEMA), spark.createDataFrame(random_rows(5, 40), SCHEMA)
    left, right = retrieval.collapse_queries(queries, ["a", "b"]), retrieval.plain_pool(pool, TASK, ["a", "b"])
    for options in (dict(), dict(diverse=False), dict(backfill=True)):
        ranked = lambda **cut: sorted(map(tuple, retrieval._ranked(compare.candidates(left, right, 2, 7, **options, **cut), 7, options.get("diverse", True), options.get("backfill", False)).collect()))
        assert ranked(block_rows=rows, slice_chars=100) == ranked()


def test_gram_index_shuffles_no_pairs(spark):
    queries, pool = spark.createDataFrame(random_rows(6, 9, 1000), SCHEMA), spark.createDataFrame(random_rows(7, 40), SCHEMA)
    got = retrieval.retrieve_indexed(queries, pool, TASK, ["a", "b"], 3, g=2)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, retrieval.retrieve(queries, pool, TASK, ["a", "b"], 3).collect()))
    assert "Generate" not in plan_of(got) and "NestedLoop" not in plan_of(got)


def test_all_pairs_with_their_bounds(spark):
    from pyspark.sql import functions as F

    queries, pool = spark.createDataFrame(random_rows(8, 9, 1000), SCHEMA), spark.createDataFrame(random_rows(9, 40), SCHEMA)
    left, right = retrieval.collapse_queries(queries, ["a", "b"]), retrieval.collapse_pool(pool, TASK, ["a", "b"])
    got = compare.all_pairs(left, right, 2, block_rows=7)
    want = left.crossJoin(right).select("q0", "q1", "p0", "p1", F.round(retrieval.similarity(["a", "b"], None), 9), retrieval.upper_bound(["a", "b"]))
    assert sorted(map(repr, map(tuple, got.collect()))) == sorted(map(repr, map(tuple, want.collect())))
    assert "NestedLoop" not in plan_of(got)


def test_pairwise_patterns_equal_all_pairs():
    from textimpute.operators.patterns import mine_group

    r = random.Random(5)
    for n in (2, 3, 30):
        texts = ["".join(r.choice("ab") for _ in range(r.randint(1, 7))) for _ in range(n)]
        common = {lcs_string(a, b) for i, a in enumerate(texts) for b in texts[:i]} - {""}
        for q in (0.01, 0.4):
            want = sorted((c, sum(c in t for t in texts)) for c in common if sum(c in t for t in texts) >= q * n)
            assert mine_group(texts, q, "pairwise") == want


def test_pairwise_patterns_build_no_automaton_a_pair(monkeypatch):
    from textimpute.functions import automaton
    from textimpute.operators.patterns import mine_group

    built, plain = [], automaton.SuffixAutomaton.__init__
    monkeypatch.setattr(automaton.SuffixAutomaton, "__init__", lambda self, *texts: built.append(1) or plain(self, *texts))
    assert ("231-", 200) in mine_group([f"231-{i:03}" for i in range(200)], 0.9, "pairwise")
    assert len(built) == 1


def test_cosines_by_blocks_equal_pair_by_pair(spark):
    import math

    r = random.Random(8)
    vec = lambda: r.choice([None, [0.0] * 5, [1.0, 2.0], [1.0, None, 3.0, 4.0, 5.0], *([float(r.randint(-2, 2)) for _ in range(5)] for _ in range(12))])
    rows = [(i, r.randint(0, 3), vec()) for i in range(50)]
    df = spark.createDataFrame(rows, "id long, label int, v array<float>")

    def cosine(a, b):
        if a is None or b is None or len(a) != len(b) or None in a or None in b or not any(a) or not any(b):
            return None
        return compare.rounded(np.array([sum(x * y for x, y in zip(a, b)) / (math.sqrt(sum(x * x for x in a)) * math.sqrt(sum(x * x for x in b)))]), 6)[0] / 1e6

    for diverse in (False, True):
        for k in (3, 45):
            got = retrieval.retrieve_embedding(df.filter("id < 10"), df.filter("id >= 10"), "id", "v", "label", k, diverse)
            want = []
            for i, _, a in rows[:10]:
                best = sorted((s is None, -(s or 0), e, str(label)) for e, label, b in rows[10:] for s in [cosine(a, b)])
                seen = set()
                if diverse:
                    best = [x for x in best if not (x[3] in seen or seen.add(x[3]))]
                want += [(i, n + 1, e, label, None if none else -s) for n, (none, s, e, label) in enumerate(best[:k])]
            assert sorted(map(tuple, got.collect())) == want
            assert "NestedLoop" not in plan_of(got) and "Cartesian" not in plan_of(got)
    left, right = (df.selectExpr("id as cells_id", "v as vector"), df.selectExpr("id as example_id", "cast(label as string) as target_value", "v as vector"))
    ranked = lambda **cut: sorted(map(tuple, retrieval._ranked(compare.vector_candidates(left, right, 4, **cut), 4, False).collect()))
    assert ranked(block_rows=3, slice_numbers=100) == ranked()


def test_window_hashes_tell_windows(spark):
    from textimpute.functions.windows import WindowSet, window_hashes

    r = random.Random(4)
    text = "".join(r.choice("ab\U0001f600") for _ in range(9000))
    hashes = window_hashes(text, 12)
    assert len({(text[i:i + 12], int(h)) for i, h in enumerate(hashes)}) == len({text[i:i + 12] for i in range(len(hashes))}) == len(set(hashes.tolist()))
    assert window_hashes("x" + text, 12)[1:].tolist() == hashes.tolist() and len(window_hashes("short", 12)) == 0
    assert WindowSet(hashes[:5]).found(hashes[3:]).tolist() == sorted(set(hashes[:5].tolist()) & set(hashes[3:].tolist()))


def test_passages_take_no_window_as_a_row(spark):
    df = spark.createDataFrame([(1, "x" * 30 + "a long passage that both hold" + "y" * 20), (2, None)], "id long, text string")
    got = retrieval.shared_passages(df, df, "id", "id", least=20)
    assert [tuple(x) for x in got.collect()] == [(1, 1, 79)] and "Generate" not in plan_of(got)


@pytest.mark.parametrize("hot", [0, 3, 1000])
def test_classes_of_hot_words_equal_all_pairs(spark, hot):
    from pyspark.sql import functions as F

    from textimpute.operators.baselines import _nearest

    r = random.Random(11)
    words = lambda: sorted(r.sample(range(4), r.randint(0, 3)) + r.sample(range(10, 40), r.randint(0, 2)))
    asked, known = [(r.randint(0, 1), i, words()) for i in range(15)], [(r.randint(0, 1), 100 + i, r.choice("uvw"), words()) for i in range(60)]
    a, b = spark.createDataFrame(asked, "c int, query_id long, wa array<long>"), spark.createDataFrame(known, "c int, example_id long, value string, wb array<long>")
    for k in (1, 4):
        want = []
        for c, i, x in asked:
            met = [(-round(len(set(x) & set(y)) / len(set(x) | set(y)), 9), e, v) for d, e, v, y in known if c == d and set(x) & set(y)]
            want += [(i, e, v, -s) for s, e, v in sorted(met)[:k]]
        got = _nearest(a, b, k, lambda shared, na, nb: shared / (na + nb - shared), ("c",), hot).select("query_id", "example_id", "value", F.round("score", 9))
        assert sorted(map(tuple, got.collect())) == sorted(want)


def test_nearest_of_a_cluster_is_one_row_not_all_rows_of_a_value(spark):
    from textimpute.operators import baselines

    many = lambda first, city, a, b: [(first + i, city, a, f"{b} r{first + i}") for i in range(1100)]
    x, y = (" ".join(f"{c}{i}" for i in range(12)) for c in "xy")
    rows = many(0, "A", x, "c1 s1") + many(2000, "A", x, "c2 s2") + many(4000, "B", x, "c1 s2") + many(6000, "C", y, "c1 s2")
    asked = [(9001, None, x, "c1 s2"), (9002, None, x, "c2 s1"), (9003, None, y, "c2 s2"), (9004, None, None, None)]  # 9002: A and B share 13 words each
    got = baselines.cluster_fill(spark.createDataFrame(rows + asked, SCHEMA), TASK, clusters=2, how="nearest")
    assert {r["query_id"]: r["answer"] for r in got.collect()} == {9001: "B", 9002: "A", 9003: "C"}


def test_clusters_do_not_depend_on_the_cut_of_the_table(spark, monkeypatch):
    from textimpute.operators import baselines

    r = random.Random(8)
    rows = [(i, r.choice("uvw") if i % 5 else None, " ".join(r.choices("abcdefgh", k=3)), " ".join(r.choices("mnopq", k=2))) for i in range(400)]
    monkeypatch.setattr(baselines, "ROWS_A_TASK", 100, raising=False)
    df = spark.createDataFrame(rows, SCHEMA)
    fills = [dict(how="mode"), dict(how="nearest")]
    one, many = ([sorted(map(tuple, baselines.cluster_fill(cut, TASK, clusters=5, **how).collect())) for how in fills] for cut in (df.coalesce(1), df.repartition(7)))
    assert one == many and len(one[0]) == 80
    assert baselines._dealt(df.coalesce(1), "id").rdd.getNumPartitions() == 4
    placed = [(x["id"], x["value"], set(x["w"]), x["cluster"]) for x in baselines._clustered(df, TASK, 5, 20, 512).collect()]
    want = []
    for i, value, w, c in placed:
        met = [(-len(w & u), v) for _, v, u, d in placed if v is not None and c == d and w & u]
        want += [(i, min(met)[1])] if value is None and met else []
    for hot in (0, 10, 1000):
        assert sorted(map(tuple, baselines.cluster_fill(df, TASK, clusters=5, how="nearest", hot=hot).collect())) == sorted(want)
