"""Estimators against exact values, engines against each other, and edge cases."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from spreadlab.functions.coins import coin, coin_below, md5_coin
from spreadlab.operators import exact, local, metrics
from spreadlab.operators.order import bfs_edges, random_edges
from spreadlab.operators.reach import closure, frontier, packed, spread_of
from spreadlab.operators.tree import root_draws
from spreadlab.plans import estimators, workloads
from spreadlab.plans.estimators import ESTIMATORS, SampleSpec, estimate, estimate_sets
from spreadlab.sources import graphs as G

EXACT, VARIANCE = 2.020416, 3.000463
RS = {"cube": 2, "stai": 3}


def graph(edges=G.EXAMPLE):
    return local.Graph(np.arange(len(edges)), *(np.array([e[k] for e in edges]) for k in (0, 1, 2)))


def run(g, seed, method, n, rep, tau=10, r=None, **options):
    scheme, selector, recursive, default = ESTIMATORS[method]
    coins = local.Coins(7, rep, "mixed")
    leaves, _ = local.leaves_of(g, g.number(seed), coins, scheme, selector, default if r is None else r, tau, n, recursive, **options)
    return leaves, local.outcomes(g, g.number(seed), coins, leaves)[0]


def test_exact_values_agree(spark):
    e = G.example(spark)
    row = exact.by_bits(spark, e, 5).collect()[0]
    assert row.spread == pytest.approx(EXACT, abs=1e-6)
    assert row.variance == pytest.approx(VARIANCE, abs=1e-6)
    assert row.total_probability == pytest.approx(1)
    assert exact.divide(spark, e, 5, 3).collect()[0].spread == pytest.approx(row.spread, abs=1e-9)


def test_worked_visiting_order(spark):
    rows = bfs_edges(G.example(spark), spark.createDataFrame([(5,)], "seed long")).orderBy("ord").collect()
    assert [(r.src, r.dst) for r in rows] == [(a, b) for a, b, _ in G.EXAMPLE]
    g = graph()
    assert [(int(g.nodes[g.src[i]]), int(g.nodes[g.dst[i]])) for i in g.bfs_order(g.number(5))] == [(a, b) for a, b, _ in G.EXAMPLE]


def test_strata_masses():
    p = np.array([0.6, 0.3])
    assert local.masses(p, "cube")[0] == pytest.approx([0.28, 0.42, 0.12, 0.18])
    pi, consumed = local.masses(p, "staircase")
    assert pi == pytest.approx([0.28, 0.60, 0.12])
    assert consumed.tolist() == [2, 1, 2]
    assert local.masses(np.random.default_rng(0).random(50), "staircase")[0].sum() == pytest.approx(1)


@pytest.mark.parametrize("method", list(ESTIMATORS))
def test_unbiased_and_exact_budget(method):
    g, n, reps = graph(), 100, 300
    means = []
    for rep in range(reps):
        _, f = run(g, 5, method, n, rep, r=RS.get(method[:4]))
        assert len(f) == n
        means.append(f.mean())
    error = np.std(means, ddof=1) / np.sqrt(reps)
    assert abs(np.mean(means) - EXACT) < 4 * error


def test_variance_order():
    g, n = graph(), 100
    relative = {m: np.var([run(g, 5, m, n, i, r=RS.get(m[:4]))[1].mean() for i in range(300)], ddof=1) * n / VARIANCE for m in ESTIMATORS}
    assert relative["cube_recursive_bfs"] < relative["cube_recursive_random"] < relative["cube_basic_random"]
    assert relative["stair_recursive_bfs"] < relative["stair_recursive_random"] < relative["stair_basic_random"]
    assert relative["cube_recursive_bfs"] < relative["single_edge_recursive"] < 0.8
    assert relative["naive"] == pytest.approx(1, abs=0.3)


def test_special_cases():
    g = graph()
    naive = run(g, 5, "naive", 40, 0)[1]
    assert (run(g, 5, "cube_recursive_bfs", 40, 0, tau=41, r=2)[1] == naive).all()  # below tau at the root
    assert (run(g, 5, "cube_recursive_bfs", 40, 0, r=11)[1] == naive).all()  # fewer edges than r
    assert (run(g, 5, "stair_basic_bfs", 40, 0, r=0)[1] == naive).all()
    cube, stair = (sorted(len(x.draws) for x in run(g, 5, m, 40, 0, r=1)[0]) for m in ("cube_basic_bfs", "stair_basic_bfs"))
    assert cube == stair  # one edge: both schemes have the same two strata
    chain = graph([(i, i + 1, 1.0) for i in range(5)] + [(0, 9, 0.0)])
    assert set(run(chain, 0, "stair_recursive_bfs", 20, 0, r=2)[1]) == {5.0}
    assert run(chain, 5, "cube_recursive_bfs", 20, 0, r=2)[1].sum() == 0  # no out-edges
    with pytest.raises(ValueError):
        run(graph([(i, i + 1, 0.5) for i in range(30)]), 0, "cube_basic_bfs", 20, 0, r=17)


def test_rounded_allocation_and_redrawn_edges():
    g = graph()
    kept, _ = run(g, 5, "cube_basic_bfs", 1000, 0, r=2, allocation="nearest_min1")
    assert sorted(len(x.draws) for x in kept) == [120, 180, 280, 420]
    means = [run(g, 5, "cube_recursive_random", 100, i, r=2, random_mode="per_node")[1].mean() for i in range(300)]
    assert abs(np.mean(means) - EXACT) < 4 * np.std(means, ddof=1) / np.sqrt(300)


def test_engines_agree(spark):
    e, s = G.example(spark), spark.createDataFrame([(5,)], "seed long")
    assert spark.range(1).select(coin(7, 0, 3, 4).alias("c")).collect()[0].c == md5_coin(7, 0, 3, 4)
    f = {r.draw: r.f for r in spread_of(frontier(e, root_draws(spark, s, 1, 70))).collect()}
    bits = packed(e, s, 70).collect()
    counts = [sum((r.bits >> (d % 64)) & 1 for r in bits if r.word == d // 64) - 1 for d in range(70)]
    assert [f[d] for d in range(70)] == counts


@pytest.mark.parametrize("method", list(ESTIMATORS))
def test_engines_agree_in_every_column(spark, method):
    e, s = G.example(spark), spark.createDataFrame([(5,), (4,), (77,)], "seed long")
    rows = {x: sorted(tuple(r) for r in estimate(e, s, method, r=RS.get(method[:4]), spec=SampleSpec(n=60, reps=2, coin="md5", engine=x)).collect()) for x in ("local", "frontier")}
    if method in ("stair_recursive_bfs", "naive"):
        rows["packed"] = sorted(tuple(r) for r in estimate(e, s, method, r=RS.get(method[:4]), spec=SampleSpec(n=60, reps=2, coin="md5", engine="packed")).collect())
    for got in rows.values():
        assert len(got) == 6
        for a, b in zip(rows["local"], got, strict=True):
            assert a[:3] == b[:3] and a[3:] == pytest.approx(b[3:], abs=1e-12)


def test_targets_agree_between_engines(spark):
    e, s = G.example(spark), spark.createDataFrame([(5,)], "seed long")
    for x in (("reaches", 2), ("reaches_within", 2, 2), ("distance", 2, 9), ("connects", (1, 4))):
        one, two = (tuple(estimate(e, s, "cube_recursive_bfs", r=2, spec=SampleSpec(n=60, coin="md5", engine=k), statistic=x).collect()[0])[3:] for k in ("local", "frontier"))
        assert one == pytest.approx(two, abs=1e-12), x
    for bad in ({"allocation": "nearest_drop"}, {"random_mode": "per_node"}):
        with pytest.raises(ValueError):
            estimate(e, s, "cube_basic_random", spec=SampleSpec(engine="frontier", **bad))
    with pytest.raises(ValueError):
        estimate(e, s, "naive", spec=SampleSpec(engine="packed"), statistic=("reaches", 2))


def test_estimated_variance_is_right():
    """The mean of the stratified estimate is the variance over runs, with single-draw leaves too."""
    g = graph()
    for method, r in (("naive", None), ("cube_basic_bfs", 2), ("cube_recursive_bfs", 2), ("stair_recursive_bfs", 3)):
        means, guesses = [], []
        for rep in range(400):
            leaves, f = run(g, 5, method, 100, rep, r=r)
            means.append(f.mean())
            guesses.append(local.stratified_variance(f, leaves, f.mean()))
        # grid slots spread draws more evenly than independent ones, so the estimate may lie above
        assert 0.8 < np.mean(guesses) / np.var(means, ddof=1) < 1.6, method


def test_packed_coins_have_their_probabilities():
    from spreadlab.functions.coins import bernoulli_words, key_of

    p = np.array([0.0, 1e-4, 0.25, 0.3, 0.5, 0.999, 1.0])
    bits = bernoulli_words(key_of(1, "x"), np.arange(7), p, np.arange(4000))
    share = np.bitwise_count(bits).sum(1) / (64 * 4000)
    assert (np.abs(share - p) <= 5 * np.sqrt(p * (1 - p) / (64 * 4000))).all()
    some = bernoulli_words(key_of(1, "x"), np.array([3, 2]), p[[3, 2]], np.array([17, 5]))
    assert (some == bits[[3, 2]][:, [17, 5]]).all()


def test_prefixes_of_orders(spark):
    rng = np.random.default_rng(3)
    pairs = sorted({(int(a), int(b)) for a, b in rng.integers(0, 40, (200, 2)) if a != b})
    e = spark.createDataFrame([(i, a, b, 0.5) for i, (a, b) in enumerate(pairs)], "edge_id long, src long, dst long, p double")
    s = spark.createDataFrame([(pairs[0][0],), (pairs[50][0],)], "seed long")
    whole = {(r.seed, r.ord): r.edge_id for r in bfs_edges(e, s).collect()}
    assert {(r.seed, r.ord): r.edge_id for r in bfs_edges(e, s, 30).collect()} == {k: v for k, v in whole.items() if k[1] < 30}
    every = {(r.rep, r.ord): r.edge_id for r in random_edges(e, 3).collect()}
    assert {(r.rep, r.ord): r.edge_id for r in random_edges(e, 3, limit=9).collect()} == {k: v for k, v in every.items() if k[1] < 9}


def test_seed_sets(spark):
    e = G.given(G.example(spark).drop("p"), 1.0)
    members = spark.createDataFrame([(0, 5), (1, 1), (1, 6), (2, 4), (2, 4), (3, 99), (4, None)], "set_id long, node long")
    for engine in ("local", "frontier"):
        got = {r.seed: r.f_hat for r in estimate_sets(e, members, "cube_recursive_bfs", r=2, spec=SampleSpec(n=20, engine=engine)).collect()}
        assert got == {0: 5.0, 1: 3.0, 2: 2.0, 3: 0.0}


def test_closure_goes_to_the_end(spark):
    chain = spark.createDataFrame([(i, i, i + 1, 1.0) for i in range(24)] + [(99, 50, 51, 1.0)], "edge_id long, src long, dst long, p double")
    assert closure(chain, spark.createDataFrame([(3,)], "seed long")).count() == 21


def test_other_targets_and_absent_seed(spark):
    e, s = G.given(G.example(spark).drop("p"), 1.0), spark.createDataFrame([(5,), (99,)], "seed long")
    got = {x: {r.seed: r.f_hat for r in estimate(e, s, "naive", spec=SampleSpec(n=10), statistic=x).collect()} for x in (("spread",), ("reaches", 2), ("reaches_within", 2, 1), ("distance", 2, 9), ("connects", (1, 4)))}
    assert got["spread",] == {5: 5.0, 99: 0.0}
    assert [got[k][5] for k in list(got)[1:]] == [1.0, 0.0, 2.0, 1.0]


def test_probabilities_are_checked(spark):
    bad = spark.createDataFrame([(0, 1, 2, None)], "edge_id long, src long, dst long, q double")
    with pytest.raises(Exception, match="probability"):
        G.given(bad, "q").collect()


def test_metrics(spark):
    rows = [("naive", 1, i, float(i % 2)) for i in range(10)] + [("x", 1, i, 0.5 + 0.1 * (i % 2)) for i in range(10)] + [(m, 2, i, 1.0) for m in ("naive", "x") for i in range(10)]
    est = spark.createDataFrame(rows, "estimator string, seed long, rep int, f_hat double")
    rel = {r.estimator: r for r in metrics.relative_variance(est).collect()}
    assert rel["x"].mean_of_ratios == pytest.approx(0.01) and rel["x"].excluded == 1 and rel["x"].seeds == 1
    assert metrics.worst_case_variance(10, 100) == pytest.approx(np.var([0] * 5 + [99] * 5, ddof=1))
    got = metrics.mse(est.filter("seed = 1"), spark.createDataFrame([(1, 0.5)], "seed long, spread double")).filter("estimator = 'x'").collect()[0]
    assert got.mse == pytest.approx(got.variance + got.bias**2)


def test_dense_ids_and_successors(spark):
    rows = spark.range(500).select((F.col("id") * 7 % 500).alias("k"), F.col("id").alias("v"))
    nxt = {r.k: r.next_v for r in G.successor(rows, "v", "k").collect()}
    v = {r.k: r.v for r in rows.collect()}
    assert all(nxt[k] == v[k + 1] for k in range(499)) and nxt[499] is None
    e = G.with_edge_ids(rows.select(F.col("k").alias("src"), F.col("v").alias("dst"))).orderBy("src", "dst").collect()
    assert [r.edge_id for r in e] == list(range(500))


def test_needed_part_gives_what_the_whole_graph_gives(spark, monkeypatch):
    rng = np.random.default_rng(3)
    ends = sorted({(int(a) + c, int(b) + c) for a, b in rng.integers(0, 60, (240, 2)) for c in (0, 1000, 2000) if a != b})
    rows = [(i, a, b, float(p)) for i, ((a, b), p) in enumerate(zip(ends, rng.random(len(ends)) * 0.4, strict=True))]
    e, s = spark.createDataFrame(rows, "edge_id long, src long, dst long, p double"), spark.createDataFrame([(ends[0][0],), (77777,)], "seed long")
    spec, methods, sent = SampleSpec(n=30, reps=1, coin="md5"), ["naive", "stair_recursive_random", "cube_basic_bfs"], []
    want = sorted(tuple(r) for r in workloads.estimates_of(e, s, methods, spec).collect())
    monkeypatch.setattr(workloads, "WHOLE_EDGES", 100)
    monkeypatch.setattr(workloads, "FIRST_EDGES", 30)  # less than a tree takes: taken again, longer
    monkeypatch.setattr(estimators, "GRAPH_BYTES", 40 * (len(rows) - 1))  # the whole graph does not fit
    collect = workloads.collect_needed
    monkeypatch.setattr(workloads, "collect_needed", lambda *a: sent.append(collect(*a)) or sent[-1])
    assert sorted(tuple(r) for r in workloads.estimates_of(e, s, methods, spec).collect()) == want and len(want) == 6
    assert [len(g.orders[0]) for g in sent] == [30, 240] and all(len(g.edge_id) < len(rows) for g in sent)


def test_coin_below_is_the_comparison(spark):
    rows = spark.range(300).select(coin(7, "order", F.col("id")).alias("u"), coin_below(0.3, 7, "order", F.col("id")).alias("low"), coin_below(1e-4, 7, "order", F.col("id")).alias("least")).collect()
    assert all(r.low == (r.u < 0.3) and r.least == (r.u < 1e-4) for r in rows) and 0 < sum(r.low for r in rows) < 300
