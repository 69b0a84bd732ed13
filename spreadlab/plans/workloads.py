"""The experiment workloads on derived graphs."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadlab.operators.metrics import reduction_pct, relative_variance
from spreadlab.plans.estimators import ESTIMATORS, SampleSpec, collect_graph, collect_needed, estimate, fits_memory
from spreadlab.storage import discard, materialize

WHOLE_EDGES = 2_000_000  # of a graph that is kept whole in memory; of a larger one only what estimates depend on
FIRST_EDGES = 4096  # of each run's random order, at first


def shared_graph(edges: DataFrame):
    """The graph, sent to the executors once for a whole workload."""
    return edges.sparkSession.sparkContext.broadcast(collect_graph(edges))


def estimates_of(edges: DataFrame, seeds: DataFrame, methods: list[str] | None = None, spec: SampleSpec = SampleSpec(reps=40), rs: dict[str, int] | None = None, tau: int = 10) -> DataFrame:  # noqa: B008
    """All estimators over the same seeds and coins (common random numbers)."""
    methods = methods or list(ESTIMATORS)

    def evaluated(graph) -> DataFrame:
        runs = [estimate(edges, seeds, m, (rs or {}).get(m), tau, spec, graph=graph) for m in methods]
        out = materialize(reduce(DataFrame.unionByName, runs), "estimates")
        if graph is not None:
            graph.unpersist()
        return out

    if spec.engine in ("auto", "local") and spec.random_mode == "per_run" and (m := edges.count()) > WHOLE_EDGES:
        limit = FIRST_EDGES
        while limit < m and (needed := collect_needed(edges, seeds, methods, spec, limit)) is not None:
            out = evaluated(edges.sparkSession.sparkContext.broadcast(needed))
            if out.filter("tree_nodes < 0").isEmpty():
                return out
            discard(out)
            limit *= 8
    return evaluated(shared_graph(edges) if spec.engine == "local" or spec.engine == "auto" and fits_memory(edges) else None)


def accuracy_table(edges: DataFrame, seeds: DataFrame, spec: SampleSpec = SampleSpec(reps=40), rs: dict[str, int] | None = None) -> DataFrame:  # noqa: B008
    """(estimator, relative variance two ways, reduction in per cent to the single-edge prior)."""
    rel = materialize(relative_variance(estimates_of(edges, seeds, None, spec, rs)), "relative")
    return rel.join(reduction_pct(rel, "single_edge_recursive"), "estimator")


def running_time(edges: DataFrame, seeds: DataFrame, methods: list[str] | None = None, spec: SampleSpec = SampleSpec(), rs: dict[str, int] | None = None) -> dict[str, float]:  # noqa: B008
    """Wall seconds per evaluation (one seed, one run), averaged over the seeds and runs of one job."""
    graph, out, n = shared_graph(edges), {}, seeds.count() * spec.reps
    for m in methods or list(ESTIMATORS):
        began = time.perf_counter()
        estimate(edges, seeds, m, (rs or {}).get(m), spec=spec, graph=graph).agg(F.avg("f_hat")).collect()
        out[m] = (time.perf_counter() - began) / n
    graph.unpersist()
    return out


def effect_of_r(edges: DataFrame, seeds: DataFrame, scheme: str, values: list[int], spec: SampleSpec = SampleSpec(reps=40)) -> DataFrame:  # noqa: B008
    """(r, estimator, mean_of_ratios, ..) of a scheme's four estimators against naive."""
    own = [m for m, (s, *_) in ESTIMATORS.items() if s == scheme and m != "single_edge_recursive"]
    tables = [relative_variance(estimates_of(edges, seeds, ["naive", *own], spec, dict.fromkeys(own, r))).withColumn("r", F.lit(r)) for r in values]
    return reduce(DataFrame.unionByName, tables)


def effect_of_n(edges: DataFrame, seeds: DataFrame, values: list[int], reps: int = 40, salt: int = 7, coin: str = "mixed") -> DataFrame:
    """(n, estimator, mean_of_ratios, ..) of the two recursive breadth-first estimators."""
    own = ["cube_recursive_bfs", "stair_recursive_bfs"]
    tables = [relative_variance(estimates_of(edges, seeds, ["naive", *own], SampleSpec(n=n, reps=reps, salt=salt, coin=coin))).withColumn("n", F.lit(n)) for n in values]
    return reduce(DataFrame.unionByName, tables)


def ablation(relative: DataFrame, this: str, that: str) -> DataFrame:
    """(family, ratio): relative variance of the estimators named with ``this`` over their counterparts named with ``that``."""
    one = relative.filter(F.col("estimator").contains(this)).select(F.replace("estimator", F.lit(this), F.lit("")).alias("family"), F.replace("estimator", F.lit(this), F.lit(that)).alias("counterpart"), F.col("mean_of_ratios").alias("a"))
    return one.join(relative.select(F.col("estimator").alias("counterpart"), F.col("mean_of_ratios").alias("b")), "counterpart").select("family", (F.col("a") / F.col("b")).alias("ratio"))


def top_influencers(edges: DataFrame, k: int, method: str = "cube_recursive_bfs", spec: SampleSpec = SampleSpec(n=200), **options) -> DataFrame:  # noqa: B008
    """(seed, f_hat): the k source nodes of the largest estimated spread; every source is evaluated."""
    seeds = edges.select(F.col("src").alias("seed")).distinct()
    means = estimate(edges, seeds, method, spec=spec, **options).groupBy("seed").agg(F.avg("f_hat").alias("f_hat"))
    return means.orderBy(F.desc("f_hat"), "seed").limit(k)
