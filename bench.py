"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS], the median of three runs each; prints one JSON line."""

from __future__ import annotations

import json
import os
import statistics
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402

from textimpute.operators.dependency import select_attributes  # noqa: E402
from textimpute.operators.problem import Task, checked, split  # noqa: E402
from textimpute.plans import queries as Q  # noqa: E402
from textimpute.plans.planner import retrieve_planned  # noqa: E402
from textimpute.sources import tables  # noqa: E402

HEADLINE = ("geo_selection", "part_selection", "wide_orders_selection", "mobile_selection", "documents_lang_selection", "topk_diverse_k10", "impute_pattern_vote", "probabilistic_repair", "geo_end_to_end")


def main() -> None:
    d = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 8))
    spark = (SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", str(cpus)).config("spark.driver.memory", "8g")
             .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    tables.ship(spark)
    Q.QUERIES["nation_dependency"](spark, d).collect()  # warm-up
    seconds, notes = {}, {}
    for name in HEADLINE:
        runs = []
        for _ in range(3):
            began = time.perf_counter()
            Q.QUERIES[name](spark, d).write.format("noop").mode("overwrite").save()
            runs.append(time.perf_counter() - began)
        seconds[name] = round(statistics.median(runs), 3)
        notes[f"{name}_runs"] = [round(x, 3) for x in runs]
        print(name, seconds[name], file=sys.stderr, flush=True)
    # the two runtimes that the reference reports: attribute selection once a task, tuple selection for a missing value
    for name, frame, task in (("geo", tables.geo_customer, Q.GEO), ("parts", tables.part_titles, Q.PARTS)):
        df = Q.missingness.mask_mcar(checked(frame(spark, d), task), task, 0.1)[0].persist()
        df.count()
        began = time.perf_counter()
        chosen = select_attributes(df, task)
        notes[f"{name}_attribute_selection_s"] = round(time.perf_counter() - began, 4)
        queries, pool = split(df, task)
        began = time.perf_counter()
        retrieve_planned(queries, pool, task, chosen.attributes).write.format("noop").mode("overwrite").save()
        n = queries.count()
        notes[f"{name}_tuple_selection_s_per_missing_value"] = round((time.perf_counter() - began) / max(1, n), 6)
        notes[f"{name}_missing_values"] = n
    print(json.dumps({"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(d.rstrip("/")), "detail": notes}))


if __name__ == "__main__":
    main()
