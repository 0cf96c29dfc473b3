"""The experiments on the given tables: accuracy against the baselines, ablations, the p-q grid, missing rates, runtimes.

    python -m textimpute.plans.experiments SF_DIR [OUT.md]

writes measured tables. Answers are those of the evidence votes, no language model; they show which parts of the method
matter on these tables and are never to be read as a model's accuracy.
"""

from __future__ import annotations

import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, metrics, missingness
from ..operators.dependency import evaluate, select_attributes
from ..operators.impute import impute
from ..operators.patterns import mine_frequent, unique_patterns, unpivot_sample
from ..operators.problem import Task, checked, split
from ..operators.prompting import token_reduction
from ..operators.retrieval import retrieve, retrieve_random
from ..operators.sampling import draw
from ..sources import tables
from . import queries as Q

LANG = Task("lang", "page_id", ("url", "title", "host", "tld"))
SETS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], Task]] = {
    "part_titles": (tables.part_titles, Q.PARTS),
    "geo_customer": (tables.geo_customer, Q.GEO),
    "pages": (tables.pages_flat, LANG),
}
BASELINES = {
    "fill_mode": baselines.fill_mode, "neighbour_ensemble": baselines.neighbour_ensemble, "neighbour_object_sim": baselines.neighbour_object_sim, "cluster_fill": baselines.cluster_fill,
    "relational_regression": baselines.relational_regression, "few_label_corrector": baselines.few_label_corrector, "probabilistic_repair": baselines.probabilistic_repair,
    "finetuned_lm": baselines.finetuned_lm,
}


def accuracy(spark: SparkSession, d: str, seeds=(1, 2)) -> list[tuple]:
    """(set, method, exact match mean, std) at 10 % missing."""
    out = []
    for name, (load, task) in SETS.items():
        df = checked(load(spark, d), task).persist()
        per: dict[str, list[float]] = {}
        for seed in seeds:
            masked, truth = missingness.mask_mcar(df, task, 0.1, seed)
            t = task.but(seed=seed)
            methods = {k: (lambda f=f: f(masked, t)) for k, f in BASELINES.items()}
            methods["allattr, random, weighted_vote"] = lambda: impute(masked, t, "weighted_vote", examples="random", attributes=list(t.candidates)).answers
            methods["localized, nearest_vote"] = lambda: impute(masked, t, "nearest_vote").answers
            methods["localized, pattern_vote"] = lambda: impute(masked, t, "pattern_vote").answers
            for method, run in methods.items():
                per.setdefault(method, []).append(metrics.exact_match(metrics.judged(run(), truth, task.row_id)).first()["exact_match"])
        for method, values in per.items():
            it = iter(values)
            stats = metrics.run_seeds(lambda _: next(it), range(len(values)))
            out.append((name, method, round(stats["mean"], 3), round(stats["std"], 3)))
    return out


def reduction(spark: SparkSession, d: str) -> list[tuple]:
    out = []
    for name, (load, task) in SETS.items():
        df = checked(load(spark, d), task).persist()
        chosen = select_attributes(df, task)
        out.append((name, len(task.candidates), len(chosen.attributes), ", ".join(chosen.attributes), round(100 * token_reduction(df, task, chosen.attributes).first()["reduction"], 1)))
    return out


def ablation(spark: SparkSession, d: str) -> list[tuple]:
    """(set, k, examples, attributes, exact match, truth among the examples)."""
    out = []
    for name, (load, task) in SETS.items():
        df = checked(load(spark, d), task).persist()
        masked, truth = missingness.mask_mcar(df, task, 0.1)
        queries, pool = split(masked, task)
        chosen = select_attributes(masked, task).attributes
        for k in (3, 10):
            for which, names in (("all", sorted(task.candidates)), ("selected", chosen)):
                for how in ("random", "diverse"):
                    found = (retrieve_random(queries, pool, task, k) if how == "random" else retrieve(queries, pool, task, names, k)).persist()
                    from ..operators.backends import weighted_vote

                    em = metrics.exact_match(metrics.judged(weighted_vote(found), truth, task.row_id)).first()["exact_match"]
                    out.append((name, k, how, which, em, metrics.retrieval_hit_rate(found, truth, task.row_id).first()["hit_rate"]))
    return out


def grid(spark: SparkSession, d: str, seeds=(1, 2)) -> list[tuple]:
    """(p, q, mean attributes kept of 16) on the wide table."""
    df = tables.wide_orders(spark, d).persist()
    kept: dict[tuple[float, float], list[int]] = {}
    for seed in seeds:
        base = Task("n_name", "row_id", tables.WIDE_CANDIDATES, seed=seed)
        long = unpivot_sample(draw(checked(df, base), base), base).persist()
        for q in Q.GRID:
            shares = [r["covered"] / r["groups"] for r in evaluate(unique_patterns(mine_frequent(long, q)), long, 0.5).collect()]
            for p in Q.GRID:
                kept.setdefault((p, q), []).append(sum(s >= p for s in shares))
    return [(p, q, sum(v) / len(v)) for (p, q), v in sorted(kept.items())]


def rates(spark: SparkSession, d: str) -> list[tuple]:
    out = []
    df = checked(tables.geo_customer(spark, d), Q.GEO).persist()
    for rate in (0.1, 0.2, 0.3, 0.4, 0.5):
        masked, truth = missingness.mask_mcar(df, Q.GEO, rate)
        answers = impute(masked, Q.GEO, "nearest_vote").answers
        out.append((rate, metrics.exact_match(metrics.judged(answers, truth, "c_custkey")).first()["exact_match"]))
    return out


def runtimes(spark: SparkSession) -> list[tuple]:
    """(phase, m, n, l, seconds): attribute selection on generated tables; tuple selection for growing numbers of queries."""
    out = []
    for m, n, size in ((10, 10, 10), (10, 10, 100), (10, 10, 1000), (20, 10, 100), (10, 50, 100), (50, 10, 100)):
        task = Task("target", "row_id", ("value",), p=0.5, q=0.5, m=m, n=n)
        df = tables.lengths(spark, m, n, size).persist()
        df.count()
        began = time.perf_counter()
        select_attributes(df, task)
        out.append(("attributes", m, n, size, round(time.perf_counter() - began, 3)))
    for asked in (20, 40, 80):
        df = tables.lengths(spark, 50, 20, 100)
        queries = df.filter(F.col("row_id") < asked).withColumn("target", F.lit(None).cast("string"))
        pool = df.filter(F.col("row_id") >= asked)
        out.append(("tuples", asked, 1000 - asked, 100, round(metrics.seconds(retrieve(queries, pool, Task("target", "row_id", ("value",)), ["value"], 10)), 3)))
    return out


def report(spark: SparkSession, d: str) -> str:
    parts = [f"# Measured on {d}\n\nExact match of evidence votes and of baselines in the style of their families; no language model was called.\n"]
    for title, head, rows in (
        ("Accuracy at 10 % missing", ("set", "method", "mean", "std"), accuracy(spark, d)),
        ("Attributes kept and words saved", ("set", "all", "kept", "names", "words saved %"), reduction(spark, d)),
        ("Ablation", ("set", "k", "examples", "attributes", "exact match (weighted vote)", "truth among examples"), ablation(spark, d)),
        ("Attributes kept of 16 by p and q", ("p", "q", "kept"), grid(spark, d)),
        ("Missing rate, geo_customer, nearest vote", ("rate", "exact match"), rates(spark, d)),
        ("Runtime on generated tables", ("phase", "m or queries", "n or pool", "l", "seconds"), runtimes(spark)),
    ):
        parts.append(f"## {title}\n\n| " + " | ".join(head) + " |\n|" + "---|" * len(head) + "\n" + "\n".join("| " + " | ".join(str(x) for x in r) + " |" for r in rows) + "\n")
    return "\n".join(parts)


if __name__ == "__main__":
    session = SparkSession.builder.master("local[*]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    session.sparkContext.setLogLevel("ERROR")
    tables.ship(session)
    tables.shared_folder(session, "experiments")  # sets the checkpoint folder
    text = report(session, sys.argv[1])
    if len(sys.argv) > 2:
        with open(sys.argv[2], "w") as f:
            f.write(text)
    print(text)
