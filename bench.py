"""Headline timings: one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1) names the tables, BENCH_CPUS the local cores.
s_*: wall seconds per evaluation (one seed, 1,000 draws) with as many evaluations side by side as seeds.
latency_*: wall seconds of one evaluation alone, its job included.
SCALES=1 runs the three larger random graphs too (the largest has 3.2 million edges), ACCURACY=1 adds the relative variances of the random and the message graph at 1,000 draws (minutes).
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from spreadlab import catalog
from spreadlab.plans.estimators import ESTIMATORS, SampleSpec
from spreadlab.plans.workloads import accuracy_table, running_time
from spreadlab.sources import graphs as G
from spreadlab.storage import materialize, ship_package

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
METHODS = list(ESTIMATORS)
FEW = ["naive", "single_edge_recursive", "cube_recursive_random", "cube_recursive_bfs", "stair_recursive_bfs"]
SCALES = [(200_000, 800_000), (400_000, 1_300_000), (600_000, 1_600_000), (800_000, 3_200_000)]


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    ship_package(spark)
    times: dict[str, float] = {}

    def timed(name: str, action) -> None:
        began = time.perf_counter()
        action()
        times[name] = round(time.perf_counter() - began, 4)

    timed("warm_up", lambda: spark.range(1000).agg(F.sum("id")).collect())
    for name in ("message", "coorder_full", "supplier_week", "trade"):
        timed(f"edges_{name}", lambda name=name: catalog.BUILDERS[name](spark, SF_DIR).agg(F.sum("w")).collect())
    er = lambda n, m: materialize(G.uniform(G.with_edge_ids(G.er(spark, n, m, kind="xxhash64")), kind="xxhash64"), "edges")
    settings = [("er", er(5000, 50616), 16, METHODS), ("message", G.prepare(G.message(spark, SF_DIR)), 16, METHODS), ("coorder", G.prepare(G.coorder(spark, SF_DIR)), 16, FEW), ("coorder_full", G.prepare(G.coorder(spark, SF_DIR, 1)), 8, FEW[::3])]
    for graph, edges, k, methods in settings:
        seeds = G.random_seeds(edges, k)
        running_time(edges, seeds, ["naive"], SampleSpec(n=64))  # warms the workers
        for method, s in running_time(edges, seeds, methods, SampleSpec(n=1000)).items():
            times[f"s_{graph}_{method}"] = round(s, 4)
        print(graph, {k: v for k, v in times.items() if graph in k}, file=sys.stderr, flush=True)
    for method, s in running_time(settings[0][1], G.random_seeds(settings[0][1], 1), ["naive", "cube_recursive_bfs"], SampleSpec(n=1000)).items():
        times[f"latency_er_{method}"] = round(s, 4)
    timed("accuracy_coorder", lambda: accuracy_table(settings[2][1], G.random_seeds(settings[2][1], 5), SampleSpec(n=200, reps=20)).collect())
    for n, m in SCALES if os.environ.get("SCALES") else SCALES[:1]:
        edges = er(n, m)
        for method, s in running_time(edges, G.random_seeds(edges, 4), ["naive", "cube_recursive_bfs"], SampleSpec(n=1000)).items():
            times[f"s_er_{n // 1000}k_{m // 1000}k_{method}"] = round(s, 4)
        print(n, m, {k: v for k, v in times.items() if f"er_{n // 1000}k" in k}, file=sys.stderr, flush=True)
    if os.environ.get("ACCURACY"):
        for graph, edges in (("er", settings[0][1]), ("message", settings[1][1]), ("message_mean_20", G.prepare(G.message(spark, SF_DIR), 20.0)), ("coorder", settings[2][1])):
            for r in accuracy_table(edges, G.random_seeds(edges, 8), SampleSpec(n=1000, reps=40)).orderBy("estimator").collect():
                print("#", graph, r.estimator, round(r.mean_of_ratios or 0, 4), round(r.ratio_of_means or 0, 4), r.seeds, flush=True)
    print(json.dumps({"metric": "total seconds of the headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(SF_DIR).removeprefix("sf")}))
    spark.stop()


if __name__ == "__main__":
    main()
