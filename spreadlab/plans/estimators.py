"""The estimators: naive, and basic or recursive stratified sampling with two schemes and two selectors."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spreadlab.operators import local
from spreadlab.operators.order import bfs_edges, random_edges
from spreadlab.operators.reach import closure, coins_thrown, frontier, outcome_of, packed, spread_of_packed
from spreadlab.operators.tree import grow, root_draws, tree_size
from spreadlab.operators.worlds import shared_nodes, spread_of_all
from spreadlab.storage import materialize

GRAPH_BYTES = 256 << 20  # of a graph that executors keep in memory
EDGE_BYTES = 40
MANY_SEEDS = 64  # from so many on, draws without strata are walked once for all seeds
CUBE_R, STAIR_R, TAU = 5, 50, 10

#: name -> (scheme, selector, recursive, r)
ESTIMATORS: dict[str, tuple[str | None, str, bool, int]] = {
    "naive": (None, "bfs", False, 0),
    "single_edge_recursive": ("cube", "random", True, 1),
    **{f"{short}_{depth}_{pick}": (scheme, pick, depth == "recursive", r) for short, scheme, r in (("cube", "cube", CUBE_R), ("stair", "staircase", STAIR_R)) for depth in ("basic", "recursive") for pick in ("random", "bfs")},
}


@dataclass(frozen=True)
class SampleSpec:
    """Draws per run, runs per seed, salt, coin kind, engine, allocation and random choice.

    coin: "md5" throws alike in every engine and in SQL; "mixed" takes each engine's fastest numbers, so
    that engines agree in distribution only. engine: "auto", "local", "frontier", "packed" or "worlds".
    """

    n: int = 1000
    reps: int = 1
    salt: int = 7
    coin: str = "mixed"
    engine: str = "auto"
    allocation: str = "grid_points"
    random_mode: str = "per_run"


RESULT = "estimator string, seed long, rep int, f_hat double, draws long, draw_variance double, mean_variance double, tree_nodes long, mean_depth double, coins long"


def fits_memory(edges: DataFrame) -> bool:
    """Whether a graph is small enough to be sent to the executors whole."""
    return edges.count() * EDGE_BYTES <= GRAPH_BYTES


def collect_graph(edges: DataFrame, **options) -> local.Graph:
    """The graph in memory; a larger one than GRAPH_BYTES is refused."""
    if not fits_memory(edges):
        raise ValueError("the graph is too large for the in-memory engine")
    e = edges.select("edge_id", "src", "dst", "p").toArrow()  # columns all the way, no objects for rows
    columns = [e[c].to_numpy() for c in ("edge_id", "src", "dst", "p")]
    del e
    return local.Graph(*columns, **options)


def collect_needed(edges: DataFrame, seeds: DataFrame, methods: list[str], spec: SampleSpec, limit: int) -> local.Graph | None:
    """The part of a graph that estimates can depend on, in memory: edges that some seed may reach and the first ``limit``
    edges of each run's random order. None where this part is still too large.
    """
    needed, orders, columns = closure(edges, seeds).select("edge_id", "src", "dst", "p"), {}, ["edge_id", "src", "dst", "p"]
    if any(ESTIMATORS[m][0] is not None and ESTIMATORS[m][1] == "random" for m in methods):
        first = materialize(random_edges(edges, spec.reps, spec.salt, "md5" if spec.coin == "md5" else "xxhash64", limit), "first-edges")
        needed = needed.unionByName(first.select(columns)).dropDuplicates(["edge_id"])
        rows = first.select("rep", "ord", "edge_id").toArrow()
        rep, nth, ids = (rows[c].to_numpy() for c in ("rep", "ord", "edge_id"))
        by_rep = np.lexsort((nth, rep))
        orders = {r: ids[by_rep][rep[by_rep] == r] for r in range(spec.reps)}
    needed = materialize(needed, "needed-edges")
    return collect_graph(needed, orders=orders, total=edges.count()) if fits_memory(needed) else None


def estimate(edges: DataFrame, seeds: DataFrame, method: str, r: int | None = None, tau: int = TAU, spec: SampleSpec = SampleSpec(), statistic: tuple = ("spread",), graph=None) -> DataFrame:  # noqa: B008
    """(estimator, seed, rep, f_hat, draws, draw_variance, mean_variance, tree_nodes, mean_depth, coins) of every seed and run.

    auto: a graph of at most GRAPH_BYTES goes to the executors once and runs are dealt to tasks; a larger
    one is joined, hop by hop, by the relational engine. Both take the same options and give the same
    columns; what an engine cannot do it refuses. Many seeds of the naive estimator's spread share worlds where edges
    go up and a world fits a task. mean_variance is the stratified estimate of the
    variance of f_hat; coins counts those thrown, one per out-edge of a reached node and draw.

    Defined cases: a seed that is not in the graph reaches nothing; seeds that repeat are estimated each
    time they appear by the in-memory engine and should be made distinct; no seeds or no edges give no
    rows or zeros; null ends of edges match no node; null probabilities count as 0.
    """
    scheme, selector, recursive, default_r = ESTIMATORS[method]
    r = default_r if r is None else r
    engine = spec.engine
    plain = (scheme is None or r == 0) and statistic == ("spread",)
    if engine == "worlds" or engine == "auto" and plain and graph is None and seeds.limit(MANY_SEEDS).count() == MANY_SEEDS:
        if plain and (nodes := shared_nodes(edges)) is not None:
            return _shared(edges, seeds, method, spec, nodes)
        if engine == "worlds":
            raise ValueError("worlds are shared where edges go up and a world fits, for the spread without strata")
    if engine == "auto":
        engine = "local" if graph is not None or fits_memory(edges) else "frontier"
    if engine == "local":
        return _local(edges, seeds, method, r, tau, spec, statistic, graph)
    if spec.allocation != "grid_points" or spec.random_mode != "per_run":
        raise ValueError("the relational engines take one grid slot per draw and one order per run")
    return _relational(edges, seeds, method, r, tau, spec, statistic, engine)


def _relational(edges: DataFrame, seeds: DataFrame, method: str, r: int, tau: int, spec: SampleSpec, statistic: tuple, engine: str) -> DataFrame:
    scheme, selector, recursive, _ = ESTIMATORS[method]
    kind = "md5" if spec.coin == "md5" else "xxhash64"
    draws, fixed = root_draws(edges.sparkSession, seeds, spec.reps, spec.n), None
    if scheme is not None and r > 0:
        order = (lambda limit: bfs_edges(edges, seeds, limit)) if selector == "bfs" else (lambda limit: random_edges(edges, spec.reps, spec.salt, kind, limit))
        plan = grow(order, draws, scheme, r, tau, None if recursive else 1, spec.salt, kind)
        draws, fixed = plan.draws, plan.fixed
    if engine == "packed":
        if statistic != ("spread",):
            raise ValueError("the packed engine estimates the spread")
        bits = materialize(packed(edges, seeds, spec.n, spec.reps, spec.salt, kind, fixed), "packed-bits")
        f = spread_of_packed(bits, spec.n)
        lanes = bits.select("seed", "rep", "node", "word", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("bit"), "bits").filter(F.call_function("shiftright", "bits", F.col("bit")).bitwiseAND(1) == 1)
        reached = lanes.select("seed", "rep", (F.col("word") * 64 + F.col("bit")).cast("long").alias("draw"), "node")
    else:
        reached = materialize(frontier(edges, draws, spec.salt, kind, fixed, statistic[2] if statistic[0] == "reaches_within" else None), "reached")
        f = outcome_of(reached, statistic)
    expanded = reached.filter(F.col("hop") < statistic[2]) if statistic[0] == "reaches_within" else reached
    met = materialize(f.join(draws.select("seed", "rep", "draw", "path"), ["seed", "rep", "draw"]), "outcomes")
    means = met.groupBy("seed", "rep").agg(F.avg("f").alias("f_hat"), F.count(F.lit(1)).alias("draws"), F.coalesce(F.var_samp("f"), F.lit(0.0)).alias("draw_variance"))
    out = means.join(_stratified_variance(met, means), ["seed", "rep"]).join(tree_size(draws), ["seed", "rep"]).join(coins_thrown(edges, expanded, fixed), ["seed", "rep"], "left")
    return out.select(F.lit(method).alias("estimator"), "seed", F.col("rep").cast("int").alias("rep"), "f_hat", "draws", "draw_variance", "mean_variance", "tree_nodes", "mean_depth", F.coalesce("coins", F.lit(0)).cast("long").alias("coins"))


def _shared(edges: DataFrame, seeds: DataFrame, method: str, spec: SampleSpec, nodes: np.ndarray) -> DataFrame:
    """All seeds in the same worlds; a draw is a leaf of one stratum."""
    found = materialize(spread_of_all(edges, nodes, spec.n, spec.reps, spec.salt, spec.coin), "worlds")
    of_run = found.groupBy("node", "rep").agg(F.avg("reached").alias("f_hat"), F.coalesce(F.var_samp("reached"), F.lit(0.0)).alias("draw_variance"), F.sum("thrown").alias("coins"))
    runs = seeds.select(F.col("seed").cast("long").alias("seed")).withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(spec.reps - 1))))
    out = runs.join(of_run.withColumnsRenamed({"node": "seed"}), ["seed", "rep"], "left")
    value = lambda c, zero=0.0: F.coalesce(c, F.lit(zero)).alias(c)
    return out.select(F.lit(method).alias("estimator"), "seed", "rep", value("f_hat"), F.lit(spec.n).cast("long").alias("draws"), value("draw_variance"), (F.coalesce("draw_variance", F.lit(0.0)) / spec.n).alias("mean_variance"), F.lit(1).cast("long").alias("tree_nodes"), F.lit(0.0).alias("mean_depth"), value("coins", 0).cast("long").alias("coins"))


def _stratified_variance(met: DataFrame, means: DataFrame) -> DataFrame:
    """(seed, rep, mean_variance) of met(seed, rep, draw, f, path); as ``local.stratified_variance``, in groups."""
    run = ["seed", "rep"]
    sized = met.withColumn("size", F.count(F.lit(1)).over(Window.partitionBy(*run, "path")))
    lone = sized.filter("size = 1").withColumn("nth", F.row_number().over(Window.partitionBy(*run).orderBy("path")) - 1).withColumn("pairs", F.floor(F.count(F.lit(1)).over(Window.partitionBy(*run)) / 2))
    paired = lone.select(*run, "f", F.concat(F.lit("pair"), F.greatest(F.lit(0), F.least(F.floor(F.col("nth") / 2), F.col("pairs") - 1)).cast("string")).alias("part"))
    parts = sized.filter("size > 1").select(*run, "f", F.col("path").alias("part")).unionByName(paired).groupBy(*run, "part").agg(F.count(F.lit(1)).alias("size"), F.var_samp("f").alias("inside"), F.avg("f").alias("mean"))
    spread = F.coalesce("inside", (F.col("mean") - F.col("f_hat")) * (F.col("mean") - F.col("f_hat")))
    return parts.join(means, run).groupBy(*run).agg((F.sum(F.col("size") * spread) / F.first(F.col("draws") * F.col("draws"))).alias("mean_variance"))


def estimate_sets(edges: DataFrame, members: DataFrame, method: str, r: int | None = None, tau: int = TAU, spec: SampleSpec = SampleSpec(), **options) -> DataFrame:  # noqa: B008
    """As ``estimate`` for members(set_id, node): ``seed`` is the set's number, its members are not counted.

    A set is a node of its own, -1 - set_id, with a sure edge to each member; those edges have ids below 0,
    so every other edge throws the coins that it throws for single seeds.
    """
    sets = members.select((-1 - F.col("set_id")).cast("long").alias("src"), F.col("node").cast("long").alias("dst")).filter("src IS NOT NULL AND dst IS NOT NULL").distinct()
    sure = sets.select((-F.row_number().over(Window.partitionBy("src").orderBy("dst")).cast("long") + F.col("src") * (1 << 32)).alias("edge_id"), "src", "dst", F.lit(1.0).alias("p"))
    sizes = sets.groupBy(F.col("src").alias("set_node")).agg(F.count(F.lit(1)).alias("members"))
    whole = materialize(edges.select("edge_id", "src", "dst", "p").unionByName(sure), "edges-of-sets")
    out = estimate(whole, sets.select(F.col("src").alias("seed")).distinct(), method, r, tau, spec, **options)
    return out.join(sizes, F.col("seed") == F.col("set_node")).withColumn("f_hat", F.col("f_hat") - F.col("members")).withColumn("seed", -1 - F.col("seed")).drop("set_node", "members")


def _local(edges: DataFrame, seeds: DataFrame, method: str, r: int, tau: int, spec: SampleSpec, statistic: tuple, graph) -> DataFrame:
    spark = edges.sparkSession
    scheme, selector, recursive, _ = ESTIMATORS[method]
    sent = graph if graph is not None else spark.sparkContext.broadcast(collect_graph(edges))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        g = sent.value
        for b in batches:
            rows = []
            for seed, rep in zip(b["seed"].tolist(), b["rep"].tolist(), strict=True):
                at, coins = g.number(seed), local.Coins(spec.salt, rep, spec.coin)
                try:
                    leaves, nodes = local.leaves_of(g, at, coins, scheme, selector, r, tau, spec.n, recursive, spec.allocation, spec.random_mode)
                except local.ShortOrder:  # the caller takes longer orders
                    rows.append((method, seed, rep, 0.0, 0, 0.0, 0.0, -1, 0.0, 0))
                    continue
                f, spent = local.outcomes(g, at, coins, leaves, statistic)
                spans = np.cumsum([0] + [len(x.draws) for x in leaves])
                by_share = spec.allocation == "grid_points"
                f_hat = f.mean() if by_share else sum(x.weight * f[a:b_].mean() for x, a, b_ in zip(leaves, spans, spans[1:], strict=False))
                depth = float(np.average([x.depth for x in leaves], weights=[len(x.draws) for x in leaves]))
                rows.append((method, seed, rep, float(f_hat), len(f), float(f.var(ddof=1)) if len(f) > 1 else 0.0, local.stratified_variance(f, leaves, f_hat, by_share), nodes, depth, spent))
            yield pd.DataFrame(rows, columns=["estimator", "seed", "rep", "f_hat", "draws", "draw_variance", "mean_variance", "tree_nodes", "mean_depth", "coins"])

    tasks = seeds.select(F.col("seed").cast("long").alias("seed")).withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(spec.reps - 1))))
    parts = max(1, min(spark.sparkContext.defaultParallelism * 4, 4096))
    return tasks.repartition(parts, "seed", "rep").mapInPandas(run, RESULT)
