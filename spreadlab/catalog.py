"""Registered queries of the estimation engine, each with its DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadlab import oracle as O  # noqa: N812
from spreadlab.functions.coins import coin, coin_sql
from spreadlab.operators import alloc, exact, metrics
from spreadlab.operators.order import bfs_edges, random_edges
from spreadlab.operators.reach import frontier, packed, spread_of
from spreadlab.operators.strata import selected, strata
from spreadlab.operators.tree import root_draws
from spreadlab.plans import workloads
from spreadlab.plans.estimators import ESTIMATORS, SampleSpec, estimate, estimate_sets
from spreadlab.sources import graphs as G  # noqa: N812
from spreadlab.storage import materialize
from spreadlab.streaming import feed

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
N, REPS = 100, 2
CHECKED = SampleSpec(n=N, reps=REPS, coin="md5")


def query(name: str, sql: str | None = None):
    def put(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return put


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recursive cube estimate with breadth-first edges on the message graph."""
    e = G.prepare(G.message(spark, sf_dir))
    return estimate(e, G.random_seeds(e, 3), "cube_recursive_bfs", spec=SampleSpec(n=200, reps=4))


# --- derived graphs -------------------------------------------------------------------------------
BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "message": G.message,
    "message_gap": G.message_gap,
    "coorder": G.coorder,
    "coorder_full": lambda s, d: G.coorder(s, d, 1),
    "supplier_week": G.supplier_week,
    "trade": G.trade,
    "nation": G.nation,
    "region": G.region,
    "hierarchy": G.hierarchy,
    "repost": G.repost,
    "links": G.links,
    "turns": G.turns,
}
for _name, _build in BUILDERS.items():
    query(f"edges_{_name}", O.GRAPHS[_name])(_build)
query("edges_knn", O.KNN)(G.knn)
query("edges_er", O.er_sql(1500, 15185))(lambda s, d: G.er(s, 1500, 15185))


@query("prob_exponential", f"SELECT edge_id, src, dst, w, round(p, 9) AS p FROM ({O.edges_sql('message')})")
def prob_exponential(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.prepare(G.message(spark, sf_dir)).withColumn("p", F.round("p", 9))


@query("prob_uniform", f"SELECT edge_id, src, dst, w, {coin_sql('11', 'edge_id')} AS p FROM ({O.edges_sql('message')})")
def prob_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.uniform(G.with_edge_ids(G.message(spark, sf_dir))).select("edge_id", "src", "dst", "w", "p")


@query("symmetrize", f"SELECT src, dst, sum(w)::BIGINT AS w FROM (SELECT src, dst, w FROM ({O.GRAPHS['coorder']}) UNION ALL SELECT dst, src, w FROM ({O.GRAPHS['coorder']})) GROUP BY 1, 2")
def symmetrize(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.symmetrize(G.coorder(spark, sf_dir))


_SUMMED = ("message", "coorder", "coorder_full", "supplier_week", "nation")


@query("graph_summary", " UNION ALL ".join(f"SELECT '{g}' AS graph, count(DISTINCT n) AS nodes, (count(*) // 2)::BIGINT AS edges FROM (SELECT unnest([src, dst]) AS n FROM ({O.GRAPHS[g]}))" for g in _SUMMED))
def graph_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    one = lambda g: BUILDERS[g](spark, sf_dir).select(F.explode(F.array("src", "dst")).alias("n")).agg(F.countDistinct("n").alias("nodes"), (F.count(F.lit(1)) / 2).cast("long").alias("edges")).select(F.lit(g).alias("graph"), "nodes", "edges")
    return reduce(DataFrame.unionByName, map(one, _SUMMED))


def message_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.prepare(G.message(spark, sf_dir))


MESSAGE = O.edges_sql("message")
ONE_SEED, THREE_SEEDS = O.seeds_sql("edges", 1), O.seeds_sql("edges", 3)


@query("seeds_random", f"WITH edges AS ({MESSAGE}) {O.seeds_sql('edges', 5)}")
def seeds_random(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.random_seeds(message_edges(spark, sf_dir), 5)


# --- exact values -----------------------------------------------------------------------------------
REGION_EDGES = 20  # five regions, every ordered pair of which trades


def region_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All edges between regions, uniform probabilities."""
    return materialize(G.uniform(G.with_edge_ids(G.region(spark, sf_dir))), "region")


REGION = f"SELECT edge_id, src, dst, w, {coin_sql('11', 'edge_id')} AS p FROM (SELECT row_number() OVER (ORDER BY src, dst) - 1 AS edge_id, * FROM ({O.GRAPHS['region']}))"


def region_seed(top: DataFrame) -> int:
    """Source of the heaviest edge."""
    return top.orderBy(F.desc("w"), "src", "dst").limit(1).collect()[0].src


HEAVIEST = "(SELECT src FROM edges ORDER BY w DESC, src, dst LIMIT 1)"


@query("world_probability", f"WITH RECURSIVE {O.worlds_sql(REGION, HEAVIEST, REGION_EDGES)} SELECT world, round(pr, 12) AS pr, f FROM w")
def world_probability(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.worlds(spark, top := region_edges(spark, sf_dir), region_seed(top)).withColumn("pr", F.round("pr", 12))


_SUMS = "round(sum(pr * f), 9) AS spread, round(sum(pr * f * f) - sum(pr * f) * sum(pr * f), 9) AS variance, round(sum(pr), 9) AS total_probability"


def _rounded(df: DataFrame) -> DataFrame:
    return df.select(*(F.round(c, 9).alias(c) for c in ("spread", "variance", "total_probability")))


PRIORITY_EDGES, PRIORITY_SEED = 10, 1  # five priorities, each to all less urgent ones; the first reaches all


def priority_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All edges between priorities, uniform probabilities."""
    return materialize(G.uniform(G.with_edge_ids(G.priority(spark, sf_dir))), "priority")


PRIORITY = f"SELECT edge_id, src, dst, w, {coin_sql('11', 'edge_id')} AS p FROM (SELECT row_number() OVER (ORDER BY src, dst) - 1 AS edge_id, * FROM ({O.GRAPHS['priority']}))"
PRIORITY_WORLDS = O.worlds_sql(PRIORITY, PRIORITY_SEED, PRIORITY_EDGES)


@query("exact_example", f"WITH RECURSIVE {PRIORITY_WORLDS} SELECT {_SUMS} FROM w")
def exact_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(exact.by_bits(spark, priority_edges(spark, sf_dir), PRIORITY_SEED))


@query("exact_region", f"WITH RECURSIVE {O.worlds_sql(REGION, HEAVIEST, REGION_EDGES)} SELECT {_SUMS} FROM w")
def exact_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(exact.by_bits(spark, top := region_edges(spark, sf_dir), region_seed(top)))


@query("exact_divide_conquer", f"WITH RECURSIVE {PRIORITY_WORLDS} SELECT r::INTEGER AS r, round(sum(pr * f), 9) AS spread FROM w, range(1, 6) t(r) GROUP BY 1")
def exact_divide_conquer(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = priority_edges(spark, sf_dir)
    return reduce(DataFrame.unionByName, [exact.divide(spark, e, PRIORITY_SEED, r).select(F.lit(r).alias("r"), F.round("spread", 9).alias("spread")) for r in range(1, 6)])


@query("exact_variance", f"WITH RECURSIVE {O.worlds_sql(REGION, HEAVIEST, REGION_EDGES)} SELECT n::INTEGER AS n, round((sum(pr * f * f) - sum(pr * f) * sum(pr * f)) / n, 12) AS variance FROM w, (VALUES (100), (1000)) t(n) GROUP BY n")
def exact_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    one = exact.by_bits(spark, top := region_edges(spark, sf_dir), region_seed(top))
    return one.select(F.explode(F.array(F.lit(100), F.lit(1000))).alias("n"), "variance").withColumn("variance", F.round(F.col("variance") / F.col("n"), 12))


@query("conditional_spread", f"WITH RECURSIVE {PRIORITY_WORLDS} SELECT i AS edge_id, status::INTEGER AS status, round(sum(pr * f) / sum(pr), 9) AS spread FROM w, range(10) e(i), range(2) s(status) WHERE (world >> i::INTEGER) & 1 = status GROUP BY 1, 2")
def conditional_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = priority_edges(spark, sf_dir)
    return reduce(DataFrame.unionByName, [exact.by_bits(spark, e, PRIORITY_SEED, {i: s}).select(F.lit(i).cast("long").alias("edge_id"), F.lit(s).alias("status"), F.round("spread", 9).alias("spread")) for i in range(10) for s in (0, 1)])


def _gap_sql(stratum: str) -> str:
    return f"""WITH RECURSIVE {O.worlds_sql(REGION, HEAVIEST, REGION_EDGES)}, s AS (SELECT {stratum} AS stratum, sum(pr) AS pi, sum(pr * f) / sum(pr) AS mu, sum(pr * f * f) / sum(pr) AS sq FROM w GROUP BY 1)
    SELECT round((sum(pi * sq) - sum(pi * mu) ** 2) / 1000, 12) AS naive, round(sum(pi * (sq - mu * mu)) / 1000, 12) AS basic, round((sum(pi * mu * mu) - sum(pi * mu) ** 2) / 1000, 12) AS gap FROM s"""


def _gap(scheme: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return exact.variance_parts(spark, top := region_edges(spark, sf_dir), region_seed(top), scheme, [0, 1, 2], 1000).select(*(F.round(c, 12).alias(c) for c in ("naive", "basic", "gap")))

    return run


query("variance_gap_cube", _gap_sql("world & 7"))(_gap("cube"))
query("variance_gap_stair", _gap_sql("CASE WHEN world & 1 = 1 THEN 1 WHEN world & 2 = 2 THEN 2 WHEN world & 4 = 4 THEN 3 ELSE 0 END"))(_gap("staircase"))


@query("recursive_gap", f"""WITH RECURSIVE {O.worlds_sql(REGION, HEAVIEST, REGION_EDGES)}, s AS (SELECT world & 7 AS a, (world >> 3) & 7 AS b, sum(pr) AS pi, sum(pr * f) / sum(pr) AS mu FROM w GROUP BY 1, 2)
    SELECT a AS stratum, round(sum(pi * mu * mu) / sum(pi) - (sum(pi * mu) / sum(pi)) ** 2, 9) AS inner_gap FROM s GROUP BY 1""")
def recursive_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What splitting each cube stratum again by the next three edges takes off its variance."""
    w = exact.worlds(spark, top := region_edges(spark, sf_dir), region_seed(top)).withColumn("stratum", exact.stratum_of("cube", [0, 1, 2], F.col("world"))).withColumn("b", exact.stratum_of("cube", [3, 4, 5], F.col("world")))
    s = w.groupBy("stratum", "b").agg(F.sum("pr").alias("pi"), (F.sum(F.col("pr") * F.col("f")) / F.sum("pr")).alias("mu"))
    mean = F.sum(F.col("pi") * F.col("mu")) / F.sum("pi")
    return s.groupBy("stratum").agg(F.round(F.sum(F.col("pi") * F.col("mu") * F.col("mu")) / F.sum("pi") - mean * mean, 9).alias("inner_gap"))


# --- orders, strata, allocation -----------------------------------------------------------------
@query("bfs_edge_order", f"WITH edges AS MATERIALIZED ({MESSAGE}), seeds AS MATERIALIZED ({ONE_SEED}), {O.bfs_sql()} SELECT (SELECT seed FROM seeds) AS seed, ord, edge_id, src, dst FROM ord")
def bfs_edge_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = message_edges(spark, sf_dir)
    return bfs_edges(e, G.random_seeds(e, 1)).select("seed", "ord", "edge_id", "src", "dst")


@query("select_random", f"SELECT rep::INTEGER AS rep, row_number() OVER (PARTITION BY rep ORDER BY {coin_sql('7', chr(39) + 'order' + chr(39), 'rep', 'edge_id')}, edge_id) - 1 AS ord, edge_id FROM ({MESSAGE}), range(3) t(rep) QUALIFY ord < 5")
def select_random(spark: SparkSession, sf_dir: str) -> DataFrame:
    return random_edges(message_edges(spark, sf_dir), 3, limit=5).select("rep", "ord", "edge_id")


def first_strata(spark: SparkSession, sf_dir: str, scheme: str, r: int) -> DataFrame:
    e = message_edges(spark, sf_dir)
    order = bfs_edges(e, G.random_seeds(e, 1), 60)
    at = order.select("seed").distinct().withColumn("cursor", F.lit(0).cast("long"))
    return strata(selected(order, at, r, ("seed",)), scheme, r, ("seed",))


def _strata_sql(scheme: str, r: int) -> str:
    return f"WITH edges AS MATERIALIZED ({MESSAGE}), seeds AS MATERIALIZED ({ONE_SEED}), {O.bfs_sql()}, {O.strata_sql(scheme, r, 'SELECT 0::BIGINT')}"


for _key, _scheme, _r in (("cube_strata", "cube", 5), ("stair_strata", "staircase", 12)):
    query(_key, f"{_strata_sql(_scheme, _r)} SELECT child, round(pi, 12) AS pi, consumed FROM strata")(lambda s, d, a=_scheme, r=_r: first_strata(s, d, a, r).select("child", F.round("pi", 12).alias("pi"), "consumed"))


@query("stair_mass_total", f"{_strata_sql('staircase', 50)} SELECT count(*) AS strata, round(sum(pi), 9) AS total FROM strata WHERE pi > 1e-300")
def stair_mass_total(spark: SparkSession, sf_dir: str) -> DataFrame:
    return first_strata(spark, sf_dir, "staircase", 50).filter("pi > 1e-300").agg(F.count(F.lit(1)).alias("strata"), F.round(F.sum("pi"), 9).alias("total"))


@query("alloc_nearest", f"{_strata_sql('cube', 5)} SELECT child, greatest(1, floor(pi * 1000 + 0.5))::BIGINT AS n_min1, floor(pi * 1000 + 0.5)::BIGINT AS n_drop FROM strata")
def alloc_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = first_strata(spark, sf_dir, "cube", 5)
    return alloc.nearest(alloc.nearest(s, 1000, 1).withColumnRenamed("n", "n_min1"), 1000, 0).select("child", "n_min1", F.col("n").alias("n_drop"))


@query("alloc_grid", f"{_strata_sql('cube', 5)} SELECT rep::INTEGER AS rep, child, count(*) AS n FROM (SELECT rep, (k + {coin_sql('7', 'rep', chr(39) * 2, 'k')}) / 1000 AS slot FROM range(3) a(rep), range(1000) b(k)) JOIN strata ON slot >= lo AND slot < hi GROUP BY 1, 2")
def alloc_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return alloc.grid(first_strata(spark, sf_dir, "cube", 5), 1000, 3, 7)


@query("alloc_optimal", f"""WITH RECURSIVE {O.worlds_sql(REGION, HEAVIEST, REGION_EDGES)}, s AS (SELECT world & 7 AS child, sum(pr) AS pi, greatest(0, round(sum(pr * f * f) / sum(pr) - (sum(pr * f) / sum(pr)) ** 2, 9)) AS variance FROM w GROUP BY 1)
    SELECT child, round(1000 * pi * sqrt(variance) / sum(pi * sqrt(variance)) OVER (), 4) AS n FROM s""")
def alloc_optimal(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = exact.worlds(spark, top := region_edges(spark, sf_dir), region_seed(top)).withColumn("child", exact.stratum_of("cube", [0, 1, 2], F.col("world")))
    mean = lambda c: F.sum(F.col("pr") * c) / F.sum("pr")
    s = w.groupBy("child").agg(F.sum("pr").alias("pi"), F.greatest(F.lit(0.0), F.round(mean(F.col("f") * F.col("f")) - mean(F.col("f")) * mean(F.col("f")), 9)).alias("variance"))
    return alloc.optimal(s, 1000).select("child", F.round("n", 4).alias("n"))


# --- naive sampling -----------------------------------------------------------------------------
NAIVE = O.naive_sql(MESSAGE, THREE_SEEDS, N, REPS)


@query("naive_spread", f"WITH RECURSIVE {NAIVE} SELECT seed, rep::INTEGER AS rep, round(avg(f), 9) AS f_hat FROM f GROUP BY 1, 2")
def naive_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = message_edges(spark, sf_dir)
    return estimate(e, G.random_seeds(e, 3), "naive", spec=CHECKED).select("seed", "rep", F.round("f_hat", 9).alias("f_hat"))


ONE_NAIVE = O.naive_sql(MESSAGE, ONE_SEED, 64, 1)


@query("naive_frontier", f"WITH RECURSIVE {ONE_NAIVE} SELECT seed, rep::INTEGER AS rep, draw, f FROM f")
def naive_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The relational engine's outcome of every draw."""
    e = message_edges(spark, sf_dir)
    return spread_of(frontier(e, root_draws(spark, G.random_seeds(e, 1), 1, 64)))


@query("naive_packed", f"WITH RECURSIVE {ONE_NAIVE} SELECT seed, rep::INTEGER AS rep, node, count(*) AS draws FROM reach GROUP BY 1, 2, 3")
def naive_packed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Draws that reach each node, by the bit-packed engine."""
    e = message_edges(spark, sf_dir)
    p = packed(e, G.random_seeds(e, 1), 64)
    return p.groupBy("seed", "rep", "node").agg(F.sum(F.bit_count("bits")).alias("draws"))


@query("naive_draw_variance", f"WITH RECURSIVE {NAIVE} SELECT seed, rep::INTEGER AS rep, round(var_samp(f), 6) AS draw_variance, round(var_samp(f) / count(*), 8) AS mean_variance FROM f GROUP BY 1, 2")
def naive_draw_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = message_edges(spark, sf_dir)
    out = estimate(e, G.random_seeds(e, 3), "naive", spec=CHECKED)
    return out.select("seed", "rep", F.round("draw_variance", 6).alias("draw_variance"), F.round("mean_variance", 8).alias("mean_variance"))


_STEPS = coin_sql("7", "0", "r.draw", "e.edge_id")


@query("cascade_steps", f"""WITH RECURSIVE edges AS MATERIALIZED ({MESSAGE}), seeds AS MATERIALIZED ({ONE_SEED}),
    {O.steps_sql(f"SELECT draw, src, dst FROM edges e, range(16) r(draw) WHERE {_STEPS} < e.p", "SELECT seed FROM seeds", 16)}
    SELECT draw, node, step::INTEGER AS step FROM d""")
def cascade_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Independent cascade by time step, to its end: the step of a node is its hop in the live graph."""
    e = message_edges(spark, sf_dir)
    return frontier(e, root_draws(spark, G.random_seeds(e, 1), 1, 16)).select("draw", "node", F.col("hop").alias("step"))


@query("relevant_edges", f"WITH RECURSIVE edges AS MATERIALIZED ({O.edges_sql('repost')}), seeds AS MATERIALIZED ({ONE_SEED}), n AS (SELECT seed AS node FROM seeds UNION SELECT dst FROM edges JOIN n ON src = node) SELECT edge_id, src, dst FROM edges WHERE src IN (SELECT node FROM n)")
def relevant_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The reached nodes come from the lines' holders; only their edges are made."""
    lines = G.holders(spark, sf_dir)
    degrees = materialize(G.out_degrees(lines), "degrees")
    reached = G.joined_by_lines(lines, G.random_seeds(degrees.filter("out > 0"), 1).select(F.col("seed").alias("node")))
    return G.repost_edges(lines, degrees.join(reached, F.col("src") == F.col("node"), "left_semi")).select("edge_id", "src", "dst")


# --- the stratified estimators --------------------------------------------------------------------
def _estimator(method: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = message_edges(spark, sf_dir)
        return estimate(e, G.random_seeds(e, 1), method, spec=CHECKED).select("seed", "rep", F.round("f_hat", 9).alias("f_hat"))

    return run


def _estimator_sql(method: str) -> str:
    scheme, selector, recursive, r = ESTIMATORS[method]
    return O.estimator_sql(MESSAGE, ONE_SEED, scheme, selector, r, recursive, N, REPS)


for _method in ESTIMATORS:
    if _method != "naive":
        query(_method, _estimator_sql(_method))(_estimator(_method))


@query("stair_recursive_frontier", _estimator_sql("stair_recursive_bfs"))
def stair_recursive_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The recursive staircase estimator on the relational engine, level by level and hop by hop."""
    e = message_edges(spark, sf_dir)
    out = estimate(e, G.random_seeds(e, 1), "stair_recursive_bfs", spec=SampleSpec(n=N, reps=REPS, coin="md5", engine="frontier"))
    return out.select("seed", "rep", F.round("f_hat", 9).alias("f_hat"))


# --- accuracy measures ----------------------------------------------------------------------------
def _both(n: int, reps: int) -> tuple[str, str]:
    naive = f"SELECT 'naive' AS estimator, seed, rep, f_hat FROM (WITH RECURSIVE {O.naive_sql(O.EXAMPLE_SQL, 'SELECT 5::BIGINT AS seed', n, reps)} SELECT seed, rep, avg(f) AS f_hat FROM f GROUP BY 1, 2)"
    cube = f"SELECT 'cube_recursive_bfs' AS estimator, seed, rep, f_hat FROM ({O.estimator_sql(O.EXAMPLE_SQL, 'SELECT 5::BIGINT AS seed', 'cube', 'bfs', 2, True, n, reps)})"
    return naive, cube


ESTIMATES_SQL = " UNION ALL ".join(_both(50, 20))


def example_estimates(spark: SparkSession) -> DataFrame:
    e, s = G.example(spark), spark.createDataFrame([(5,)], "seed long")
    return workloads.estimates_of(e, s, ["naive", "cube_recursive_bfs"], SampleSpec(n=50, reps=20, coin="md5"), {"cube_recursive_bfs": 2})


_REL = f"WITH e AS ({ESTIMATES_SQL}), v AS (SELECT estimator, seed, var_samp(f_hat) AS v FROM e GROUP BY 1, 2), x AS (SELECT a.estimator, avg(a.v / b.v) AS m, sum(a.v) / sum(b.v) AS q, count(*) AS seeds FROM v a JOIN v b ON a.seed = b.seed AND b.estimator = 'naive' GROUP BY 1)"


@query("replicate_variance", f"WITH e AS ({ESTIMATES_SQL}) SELECT estimator, seed, round(avg(f_hat), 9) AS mean, round(var_samp(f_hat), 9) AS variance, count(*) AS reps FROM e GROUP BY 1, 2")
def replicate_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.replicate_variance(example_estimates(spark)).withColumns({c: F.round(c, 9) for c in ("mean", "variance")})


@query("relative_variance", f"{_REL} SELECT estimator, round(m, 6) AS mean_of_ratios, round(q, 6) AS ratio_of_means, seeds, 0::BIGINT AS excluded FROM x")
def relative_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.relative_variance(example_estimates(spark)).withColumns({c: F.round(c, 6) for c in ("mean_of_ratios", "ratio_of_means")})


@query("reduction_pct", f"{_REL} SELECT estimator, round(100 * ((SELECT m FROM x WHERE estimator = 'naive') / m - 1), 4) AS reduction FROM x")
def reduction_pct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.reduction_pct(metrics.relative_variance(example_estimates(spark)), "naive").withColumn("reduction", F.round("reduction", 4))


@query("mse_bias", f"WITH e AS ({ESTIMATES_SQL}) SELECT estimator, seed, round(avg((f_hat - 2.020416) ** 2), 9) AS mse, round(avg(f_hat - 2.020416), 9) AS bias, round(var_pop(f_hat), 9) AS variance, round(avg(f_hat - 2.020416) / (stddev_samp(f_hat) / sqrt(count(*))), 6) AS z FROM e GROUP BY 1, 2")
def mse_bias(spark: SparkSession, sf_dir: str) -> DataFrame:
    truth = spark.createDataFrame([(5, 2.020416)], "seed long, spread double")
    out = metrics.mse(example_estimates(spark), truth)
    return out.withColumns({c: F.round(c, 9) for c in ("mse", "bias", "variance")} | {"z": F.round("z", 6)})


@query("worst_case_variance", "SELECT o_custkey AS seed, n, round(var_samp(CASE WHEN i < n / 2 THEN 0 ELSE 99 END), 6) AS measured, round(n * 9801.0 / (4 * (n - 1)), 6) AS formula FROM (SELECT o_custkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) - 1 AS i, count(*) OVER (PARTITION BY o_custkey) AS n FROM orders) WHERE n > 1 GROUP BY 1, 2")
def worst_case_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each customer's orders as draws, half of which reach nothing and half all of 100 nodes, against the bound."""
    own = Window.partitionBy("o_custkey")
    rows = G.read(spark, sf_dir, "orders").select(F.col("o_custkey").alias("seed"), (F.row_number().over(own.orderBy("o_orderkey")) - 1).alias("i"), F.count(F.lit(1)).over(own).alias("n")).filter("n > 1")
    out = rows.groupBy("seed", "n").agg(F.round(F.var_samp(F.when(F.col("i") < F.col("n") / 2, 0).otherwise(99)), 6).alias("measured"))
    return out.withColumn("formula", F.round(F.col("n") * 9801.0 / (4 * (F.col("n") - 1)), 6))


# --- closed forms ----------------------------------------------------------------------------------
@query("spread_closed_bipartite", f"SELECT src AS seed, round(sum(1 - exp(-w / 2.0::DOUBLE)), 6) AS spread FROM ({O.GRAPHS['trade']}) GROUP BY 1")
def spread_closed_bipartite(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Depth one: the sum of the probabilities."""
    return G.exponential(G.trade(spark, sf_dir)).groupBy(F.col("src").alias("seed")).agg(F.round(F.sum("p"), 6).alias("spread"))


@query("spread_closed_tree", f"WITH e AS (SELECT src, dst, {coin_sql('11', 'src', 'dst')} AS p FROM ({O.GRAPHS['hierarchy']})) SELECT a.src AS seed, round(sum(own_p) + sum(through), 6) AS spread FROM (SELECT a.src, a.dst, any_value(a.p) AS own_p, coalesce(sum(a.p * b.p), 0) AS through FROM e a LEFT JOIN e b ON b.src = a.dst GROUP BY 1, 2) a GROUP BY 1")
def spread_closed_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trees: the sum over nodes of the product along the path; every inner node is a seed."""
    e = G.hierarchy(spark, sf_dir).withColumn("p", coin(11, F.col("src"), F.col("dst")))
    low = e.select(F.col("src").alias("dst"), F.col("p").alias("p2")).groupBy("dst").agg(F.sum("p2").alias("below"))
    return e.join(low, "dst", "left").groupBy(F.col("src").alias("seed")).agg(F.round(F.sum(F.col("p") * (1 + F.coalesce("below", F.lit(0.0)))), 6).alias("spread"))


@query("spread_closed_path", "WITH c AS (SELECT conv_id, count(DISTINCT turn) AS n FROM conversations GROUP BY 1) SELECT conv_id * 1000 AS seed, round(sum(0.5 ** k), 9) AS spread FROM c, range(1, 200) t(k) WHERE k < n GROUP BY 1")
def spread_closed_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paths with p = 1/2: the sum of the products of a prefix."""
    c = G.read(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.countDistinct("turn").alias("n")).filter("n > 1")
    return c.select((F.col("conv_id") * 1000).alias("seed"), F.round(1 - F.pow(F.lit(0.5), F.col("n") - 1), 9).alias("spread"))


# --- other target functions -------------------------------------------------------------------------
_HOPS = f"""edges AS MATERIALIZED ({O.edges_sql('repost', 1.0)}), seeds AS MATERIALIZED (SELECT src AS seed FROM edges GROUP BY 1 ORDER BY count(*) DESC, src LIMIT 1), tg AS (SELECT dst AS t FROM edges WHERE src = (SELECT seed FROM seeds) ORDER BY dst LIMIT 2),
    {O.steps_sql(f"SELECT draw, src, dst FROM edges e, range({N}) r(draw) WHERE {_STEPS} < e.p", "SELECT seed FROM seeds", N)}"""


def _target(statistic: Callable[[list[int]], tuple], engine: str = "auto"):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        lines = G.holders(spark, sf_dir)
        degrees = materialize(G.out_degrees(lines), "degrees")
        top = degrees.orderBy(F.desc("out"), "src").limit(1)
        seed = top.collect()[0].src
        targets = [r.dst for r in G.repost_edges(lines, top).orderBy("dst").limit(2).collect()]
        # an edge that lies on no path from the seed to a target changes no outcome
        s = spark.createDataFrame([(seed,)], "seed long")
        before = G.joined_by_lines(lines, spark.createDataFrame([(t,) for t in targets], "node long"), forward=False)
        between = G.joined_by_lines(lines, s.select(F.col("seed").alias("node")), within=before)
        e = G.repost_edges(lines, degrees.join(between, F.col("src") == F.col("node"), "left_semi"), 1.0)
        e = materialize(e.join(between, F.col("dst") == F.col("node"), "left_semi"), "edges")
        out = estimate(e, s, "naive", spec=SampleSpec(n=N, coin="md5", engine=engine), statistic=statistic(targets))
        return out.select("seed", F.round("f_hat", 9).alias("f_hat"))

    return run


_SEED = "(SELECT seed FROM seeds) AS seed"
query("reach_target", f"WITH RECURSIVE {_HOPS} SELECT {_SEED}, round(count(*) / {N}.0, 9) AS f_hat FROM d WHERE node = (SELECT max(t) FROM tg)")(_target(lambda t: ("reaches", t[-1])))
query("reach_within", f"WITH RECURSIVE {_HOPS} SELECT {_SEED}, round(count(*) / {N}.0, 9) AS f_hat FROM d WHERE node = (SELECT max(t) FROM tg) AND step <= 2")(_target(lambda t: ("reaches_within", t[-1], 2)))
query("distance_target", f"WITH RECURSIVE {_HOPS} SELECT {_SEED}, round((sum(step) + 10 * ({N} - count(*))) / {N}.0, 9) AS f_hat FROM d WHERE node = (SELECT max(t) FROM tg)")(_target(lambda t: ("distance", t[-1], 10)))
query("connects_terminals", f"WITH RECURSIVE {_HOPS}, c AS (SELECT draw FROM d WHERE node IN (SELECT t FROM tg) GROUP BY 1 HAVING count(*) = (SELECT count(*) FROM tg)) SELECT {_SEED}, round(count(*) / {N}.0, 9) AS f_hat FROM c")(_target(lambda t: ("connects", tuple(t))))


# --- workloads -------------------------------------------------------------------------------------
@query("top_influencers", f"WITH RECURSIVE {O.naive_sql(O.edges_sql('repost'), 'SELECT DISTINCT src AS seed FROM edges', 20, 1)} SELECT seed, round(avg(f), 9) AS f_hat FROM f GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10")
def top_influencers(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = G.prepare_repost(spark, sf_dir)
    return workloads.top_influencers(e, 10, "naive", SampleSpec(n=20, coin="md5")).withColumn("f_hat", F.round("f_hat", 9))


@query("accuracy_rollup", f"WITH e AS ({ESTIMATES_SQL}) SELECT estimator, seed, round(avg(f_hat), 9) AS f_hat, count(*) AS runs FROM e GROUP BY ROLLUP (estimator, seed)")
def accuracy_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return example_estimates(spark).rollup("estimator", "seed").agg(F.round(F.avg("f_hat"), 9).alias("f_hat"), F.count(F.lit(1)).alias("runs"))


def _measured(df: DataFrame) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in ("mean_of_ratios", "ratio_of_means", "reduction") if c in df.columns})


def _sql_edges(graph: str, mean: float | None) -> str:
    if mean is not None:
        return O.edges_sql(graph, mean)
    return f"SELECT edge_id, src, dst, w, {coin_sql('11', 'edge_id')} AS p FROM (SELECT row_number() OVER (ORDER BY src, dst) - 1 AS edge_id, src, dst, w FROM ({graph}))"


_RELATIVE = "estimator, round(mean_of_ratios, 6) AS mean_of_ratios, round(ratio_of_means, 6) AS ratio_of_means, seeds, excluded"
_REDUCTION = f"SELECT {_RELATIVE}, round(100 * ((SELECT mean_of_ratios FROM rel WHERE estimator = 'single_edge_recursive') / mean_of_ratios - 1), 6) AS reduction FROM rel"


def accuracy(name: str, build: Callable[[SparkSession, str], DataFrame], graph: str, mean: float | None, seeds: int, reps: int, n: int, **options) -> None:
    """A table of all estimators' relative variances on a graph (mean None: uniform probabilities), with its SQL."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = G.with_edge_ids(build(spark, sf_dir))
        e = G.exponential(e, mean) if mean is not None else materialize(G.uniform(e), "edges")
        return _measured(workloads.accuracy_table(e, G.random_seeds(e, seeds), SampleSpec(n=n, reps=reps, coin="md5")))

    estimates = O.estimates_sql(_sql_edges(graph, mean), seeds, ESTIMATORS, n, reps, **options)
    query(name, f"WITH {O.relative_sql(estimates)} {_REDUCTION}")(run)


# Sizes that DuckDB and md5 coins can check; bench.py runs the full settings, the README has its tables.
accuracy("workload_er", lambda s, d: G.er(s, 1500, 3000), O.er_sql(1500, 3000), None, 3, 8, 100, levels=40, most_cursor=800)
accuracy("workload_message", G.message, "message", 20.0, 3, 8, 100, most_cursor=800)
accuracy("workload_coorder", G.coorder, "coorder", 2.0, 3, 8, 100, levels=24, most_cursor=800)
accuracy("workload_supplier_week", G.supplier_week, "supplier_week", 400.0, 2, 6, 60, levels=16, most_cursor=1200)
accuracy("workload_coorder_full", lambda s, d: G.coorder(s, d, 1), "coorder_full", 150.0, 2, 6, 60, levels=40, most_cursor=1200)


def _swept(values: dict[str, list], spec_of, graph: Callable[[SparkSession, str], DataFrame], seeds: int):
    """Sweep of one parameter: (parameter, estimator, relative variance) rows, in md5 coins."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = G.prepare(graph(spark, sf_dir))
        s = G.random_seeds(e, seeds)
        return _measured(reduce(DataFrame.unionByName, [part for scheme, some in values.items() for part in spec_of(e, s, scheme, some)]))

    return run


def _own(scheme: str) -> dict[str, tuple]:
    return {m: v for m, v in ESTIMATORS.items() if v[0] == scheme and m != "single_edge_recursive"}


R_VALUES = {"cube": [1, 2, 3, 5, 10], "staircase": [10, 20, 30, 50, 70]}
N_VALUES = [200, 500, 1000, 2000, 5000]
R_SPEC = SampleSpec(n=40, reps=5, coin="md5")
NAIVE_METHOD = {"naive": ESTIMATORS["naive"]}


def _r_sql(scheme: str, r: int) -> str:
    methods = NAIVE_METHOD | {m: (v[0], v[1], v[2], r) for m, v in _own(scheme).items()}
    return f"SELECT {r} AS r, {_RELATIVE} FROM (WITH {O.relative_sql(O.estimates_sql(O.edges_sql('coorder'), 2, methods, R_SPEC.n, R_SPEC.reps, levels=24, most_cursor=800))} SELECT * FROM rel)"


query("workload_effect_of_r", " UNION ALL ".join(_r_sql(scheme, r) for scheme, some in R_VALUES.items() for r in some))(_swept(R_VALUES, lambda e, s, scheme, some: [workloads.effect_of_r(e, s, scheme, some, R_SPEC)], G.coorder, 2))


def _n_sql(n: int) -> str:
    methods = NAIVE_METHOD | {m: ESTIMATORS[m] for m in ("cube_recursive_bfs", "stair_recursive_bfs")}
    return f"SELECT {n} AS n, {_RELATIVE} FROM (WITH {O.relative_sql(O.estimates_sql(O.edges_sql('coorder'), 2, methods, n, 4, levels=24, most_cursor=1600))} SELECT * FROM rel)"


query("workload_effect_of_n", " UNION ALL ".join(map(_n_sql, N_VALUES)))(_swept({"": N_VALUES}, lambda e, s, _, some: [workloads.effect_of_n(e, s, some, 4, coin="md5")], G.coorder, 2))


@query("ablation_selector", f"""WITH {O.relative_sql(O.estimates_sql(O.edges_sql('message', 20.0), 3, ESTIMATORS, 60, 6, most_cursor=800))}
    SELECT replace(a.estimator, '_bfs', '') AS family, round(a.mean_of_ratios / b.mean_of_ratios, 6) AS bfs_over_random FROM rel a JOIN rel b ON b.estimator = replace(a.estimator, '_bfs', '_random') WHERE contains(a.estimator, '_bfs')""")
def ablation_selector(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Breadth-first against random choice of edges: ratio of the relative variances."""
    return workloads.ablation(_message_relative(spark, sf_dir), "_bfs", "_random").select(F.col("family"), F.round("ratio", 6).alias("bfs_over_random"))


@query("ablation_recursion", f"""WITH {O.relative_sql(O.estimates_sql(O.edges_sql('message', 20.0), 3, ESTIMATORS, 60, 6, most_cursor=800))}
    SELECT replace(a.estimator, '_recursive', '') AS family, round(a.mean_of_ratios / b.mean_of_ratios, 6) AS recursive_over_basic FROM rel a JOIN rel b ON b.estimator = replace(a.estimator, '_recursive', '_basic') WHERE contains(a.estimator, '_recursive')""")
def ablation_recursion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recursive against basic stratification: ratio of the relative variances."""
    return workloads.ablation(_message_relative(spark, sf_dir), "_recursive", "_basic").select(F.col("family"), F.round("ratio", 6).alias("recursive_over_basic"))


def _message_relative(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = G.prepare(G.message(spark, sf_dir), 20.0)
    return materialize(metrics.relative_variance(workloads.estimates_of(e, G.random_seeds(e, 3), None, SampleSpec(n=60, reps=6, coin="md5"))), "relative")


SCALES = [(2000, 8000), (4000, 13000), (6000, 16000), (8000, 32000)]
SCALED = ["naive", "cube_basic_random", "cube_recursive_random", "stair_basic_random", "stair_recursive_random"]


@query("workload_scalability", " UNION ALL ".join(f"SELECT {n} AS nodes, {m} AS edges, estimator, seed, rep::INTEGER AS rep, round(f_hat, 9) AS f_hat FROM ({O.estimates_sql(_sql_edges(O.er_sql(n, m), None), 1, {x: ESTIMATORS[x] for x in SCALED}, 20, 1)})" for n, m in SCALES))
def scalability(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimates on random graphs of four sizes, the reference's divided by a hundred; bench.py times the full ones."""
    parts = []
    for n, m in SCALES:
        e = materialize(G.uniform(G.with_edge_ids(G.er(spark, n, m))), "edges")
        parts.append(workloads.estimates_of(e, G.random_seeds(e, 1), SCALED, SampleSpec(n=20, coin="md5")).select(F.lit(n).alias("nodes"), F.lit(m).alias("edges"), "estimator", "seed", "rep", F.round("f_hat", 9).alias("f_hat")))
    return reduce(DataFrame.unionByName, parts)


# --- variance, work, seed sets ---------------------------------------------------------------------
_SCHEME, _SELECTOR, _RECURSIVE, _R = ESTIMATORS["cube_recursive_bfs"]
_DRAWS = O.estimator_sql(MESSAGE, ONE_SEED, _SCHEME, _SELECTOR, _R, _RECURSIVE, N, REPS, draws=True)


@query("stratified_variance", f"""WITH d AS ({_DRAWS}), m AS (SELECT rep, avg(f) AS f_hat, count(*) AS n FROM d GROUP BY 1), z AS (SELECT *, count(*) OVER (PARTITION BY rep, path) AS size FROM d),
    l AS (SELECT rep, f, row_number() OVER (PARTITION BY rep ORDER BY path) - 1 AS nth, count(*) OVER (PARTITION BY rep) // 2 AS pairs FROM z WHERE size = 1),
    g AS (SELECT rep, f, path AS part FROM z WHERE size > 1 UNION ALL SELECT rep, f, 'pair' || greatest(0, least(nth // 2, pairs - 1)) FROM l),
    p AS (SELECT rep, part, count(*) AS size, var_samp(f) AS inside, avg(f) AS mean FROM g GROUP BY 1, 2)
    SELECT (SELECT any_value(seed) FROM d) AS seed, p.rep::INTEGER AS rep, round(sum(size * coalesce(inside, (mean - f_hat) ** 2)) / any_value(n * n), 8) AS mean_variance FROM p JOIN m USING (rep) GROUP BY p.rep""")
def stratified_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The plug-in estimate of a stratified mean's variance, leaf by leaf."""
    e = message_edges(spark, sf_dir)
    return estimate(e, G.random_seeds(e, 1), "cube_recursive_bfs", spec=CHECKED).select("seed", "rep", F.round("mean_variance", 8).alias("mean_variance"))


@query("work_counters", f"""WITH d AS ({_DRAWS}), n AS (SELECT rep, count(DISTINCT path[1:i]) AS tree_nodes FROM (SELECT DISTINCT rep, path FROM d), LATERAL (SELECT i FROM range(length(path) + 1) t(i) WHERE i = length(path) OR path[i + 1] = '.') GROUP BY 1)
    SELECT 'cube_recursive_bfs' AS estimator, avg(draws) AS draws, avg(coins) AS coins, avg(tree_nodes) AS tree_nodes, round(avg(mean_depth), 9) AS mean_depth
    FROM (SELECT rep, count(*)::DOUBLE AS draws, sum(coins) AS coins, avg(length(path) - length(replace(path, '.', ''))) AS mean_depth FROM d GROUP BY 1) JOIN n USING (rep)""")
def work_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Draws, coins thrown, tree nodes and depth of a run, averaged."""
    e = message_edges(spark, sf_dir)
    return metrics.counters(estimate(e, G.random_seeds(e, 1), "cube_recursive_bfs", spec=CHECKED)).withColumn("mean_depth", F.round("mean_depth", 9))


@query("seed_set_spread", f"""WITH RECURSIVE edges AS MATERIALIZED ({MESSAGE}), members AS MATERIALIZED (SELECT (row_number() OVER (ORDER BY {coin_sql('5', 'seed')}, seed) - 1) // 3 AS set_id, seed AS node FROM ({O.seeds_sql('edges', 6)})),
    reach AS (SELECT set_id, draw, node FROM members, range({N}) b(draw) UNION SELECT r.set_id, r.draw, e.dst FROM reach r JOIN edges e ON e.src = r.node WHERE {coin_sql('7', '0', 'r.draw', 'e.edge_id')} < e.p)
    SELECT set_id AS seed, round(avg(f), 9) AS f_hat FROM (SELECT set_id, draw, count(*) - 3 AS f FROM reach GROUP BY 1, 2) GROUP BY 1""")
def seed_set_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two sets of three nodes each."""
    e = message_edges(spark, sf_dir)
    h = Window.orderBy(coin(5, F.col("seed")), "seed")
    members = G.random_seeds(e, 6).select(F.floor((F.row_number().over(h) - 1) / 3).alias("set_id"), F.col("seed").alias("node"))
    return estimate_sets(e, members, "naive", spec=SampleSpec(n=N, coin="md5")).select("seed", F.round("f_hat", 9).alias("f_hat"))


def _target_relational(statistic: Callable[[list[int]], tuple]):
    return _target(statistic, "frontier")


query("distance_relational", ORACLES["distance_target"])(_target_relational(lambda t: ("distance", t[-1], 10)))
query("connects_relational", ORACLES["connects_terminals"])(_target_relational(lambda t: ("connects", tuple(t))))


@query("naive_packed_spread", f"WITH RECURSIVE {ONE_NAIVE} SELECT seed, rep::INTEGER AS rep, round(avg(f), 9) AS f_hat FROM f GROUP BY 1, 2")
def naive_packed_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The bit-packed engine behind ``estimate``."""
    e = message_edges(spark, sf_dir)
    return estimate(e, G.random_seeds(e, 1), "naive", spec=SampleSpec(n=64, coin="md5", engine="packed")).select("seed", "rep", F.round("f_hat", 9).alias("f_hat"))


# --- streaming ---------------------------------------------------------------------------------------
@query("stream_edges", O.GRAPHS["message"])
def stream_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The message graph from the event stream, its last purchase kept as state."""
    return G.weighted(feed.drain(feed.successor_edges(feed.event_stream(spark, sf_dir)), "stream-edges"))


@query("stream_windows", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS day, user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2, 3")
def stream_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts, complete mode's equal: every window is written once the stream is drained."""
    e = feed.event_stream(spark, sf_dir)
    out = e.groupBy(F.window("ts", "1 day"), "user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return feed.drain_complete(out, "stream_windows_table").select(F.col("window.start").alias("day"), "user_id", "event_type", "n")
