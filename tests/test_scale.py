"""Queries that larger tables need: the same rows, made with less work."""

import hashlib
import itertools
from collections import Counter
from datetime import datetime, timedelta

import numpy as np

from spreadlab.functions import coins
from spreadlab.operators.order import random_edges
from spreadlab.plans import estimators
from spreadlab.plans.estimators import SampleSpec
from spreadlab.sources import graphs as G


def plan_of(df):
    return df._jdf.queryExecution().toString()


def test_md5_coins_side_by_side(monkeypatch):
    """Numbers of any length and sign, heads of any length; a few keys are hashed one after another."""
    rng = np.random.default_rng(2)
    keys = np.concatenate([np.arange(-120, 120), 10 ** np.arange(19), 10 ** np.arange(19) - 1, rng.integers(-(1 << 63), (1 << 63) - 1, 50), [(1 << 63) - 1, -(1 << 63)]])
    heads = []
    one = coins._md5_heads
    monkeypatch.setattr(coins, "MD5_FEWEST", 8)
    monkeypatch.setattr(coins, "MD5_BLOCK", 100)
    monkeypatch.setattr(coins, "_md5_heads", lambda words, n: heads.append(n) or one(words, n))
    for head in ("7|0|3", "", "h" * 34, "h" * 35, "7|0|" + ".31" * 30):
        want = [int(hashlib.md5(f"{head}|{k}".encode()).hexdigest()[:8], 16) / 2**32 for k in keys.tolist()]
        assert coins.md5_coins(head, keys).tolist() == want
    assert sum(heads) == 3 * len(keys)
    assert coins.md5_coins("x", np.zeros(0, np.int64)).tolist() == []


def test_tally_counts_pairs():
    rng = np.random.default_rng(3)
    for scale in (1, 1 << 58):  # keys of the second do not fit 64 bits
        a, b, w = rng.integers(-8, 8, 400) * scale, rng.integers(-8, 8, 400) * scale, rng.integers(1, 5, 400)
        count, total = Counter(zip(a.tolist(), b.tolist(), strict=True)), Counter()
        for x, y, n in zip(a.tolist(), b.tolist(), w.tolist(), strict=True):
            total[x, y] += n
        for got, want in ((G.tally(a, b), count), (G.tally(a, b, w), total)):
            assert [(x, y, n) for x, y, n in zip(*(v.tolist() for v in got), strict=True)] == [(*k, want[k]) for k in sorted(want)]


def test_coorder_is_counted_without_a_join(spark, tmp_path, monkeypatch):
    rng = np.random.default_rng(4)
    rows = [(int(o), int(p)) for o, p in zip(rng.integers(0, 60, 400), rng.integers(-30, 30, 400), strict=True)]
    spark.createDataFrame([*rows, (None, 3), (None, 4), (1, None)], "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    monkeypatch.setattr(G, "TASK_ROWS", 50)
    monkeypatch.setattr(G, "PAIRS", 40)
    want = Counter(pair for o in range(60) for pair in itertools.combinations(sorted({p for k, p in rows if k == o}), 2))
    for least in (1, 2):
        made = G.coorder(spark, str(tmp_path), least)
        assert "Join" not in plan_of(made)
        got = sorted((r.edge_id, r.src, r.dst, r.w) for r in G.with_edge_ids(made).collect())
        assert got == [(i, *k, want[k]) for i, k in enumerate(sorted(k for k in want if want[k] >= least))]


def test_supplier_week_is_counted_without_a_join(spark, tmp_path, monkeypatch):
    rng = np.random.default_rng(5)
    day = datetime(1969, 12, 20)
    orders = [(int(k), int(c), int(d)) for k, c, d in zip(rng.integers(0, 90, 100), rng.integers(-12, 12, 100), rng.integers(0, 30, 100), strict=True)]  # some keys repeat
    lines = [(int(k), int(s)) for k, s in zip(rng.integers(0, 100, 300), rng.integers(0, 5, 300), strict=True)]
    table = [(k, c, day + timedelta(days=d, hours=5)) for k, c, d in orders]
    spark.createDataFrame([*table, (None, 1, day), (3, None, day), (4, 2, None)], "o_orderkey long, o_custkey long, o_orderdate timestamp").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame([*lines, (None, 1), (5, None)], "l_orderkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    monkeypatch.setattr(G, "TASK_ROWS", 40)
    monkeypatch.setattr(G, "PAIRS", 30)
    sold = {(s, c, d) for k, s in lines for o, c, d in orders if o == k}
    for days in (7, 3):
        want = Counter((a, b) for (s, a, x), (t, b, y) in itertools.product(sold, repeat=2) if s == t and 1 <= y - x <= days and a != b)
        made = G.supplier_week(spark, str(tmp_path), days)
        assert "Join" not in plan_of(made)
        assert sorted((r.edge_id, r.src, r.dst, r.w) for r in G.with_edge_ids(made).collect()) == [(i, *k, want[k]) for i, k in enumerate(sorted(want))]


def test_empty_tables_make_empty_graphs(spark, tmp_path):
    spark.createDataFrame([], "l_orderkey long, l_partkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([], "o_orderkey long, o_custkey long, o_orderdate timestamp").write.parquet(f"{tmp_path}/orders.parquet")
    for made in (G.coorder(spark, str(tmp_path)), G.supplier_week(spark, str(tmp_path))):
        assert G.with_edge_ids(made).collect() == []


def test_first_random_edges_are_those_of_the_whole_order(spark):
    edges = spark.range(4000).selectExpr("id AS edge_id", "id AS src", "id + 1 AS dst", "0.5D AS p")
    key = lambda r: (r.rep, r.ord, r.edge_id)
    whole = sorted(key(r) for r in random_edges(edges, 3, 7).filter("ord < 200").collect())
    assert sorted(key(r) for r in random_edges(edges, 3, 7, limit=200).collect()) == whole


def test_many_seeds_share_worlds(spark, monkeypatch):
    """The same rows as from runs of single seeds, with each coin thrown once; packed pieces may overlap."""
    rng = np.random.default_rng(6)
    ends = sorted({(int(min(x)), int(max(x))) for x in rng.integers(-90, 90, (700, 2)) * 3 if x[0] != x[1]})
    ids = rng.permutation(len(ends)).tolist()
    edges = spark.createDataFrame([(i, a, b, (i % 5) / 4) for i, (a, b) in zip(ids, ends, strict=True)], "edge_id long, src long, dst long, p double").repartition(3)
    seeds = spark.createDataFrame([(int(s),) for s in range(-280, 280, 2)], "seed long")
    spec = lambda engine: SampleSpec(n=7, reps=2, coin="md5", engine=engine)
    key = lambda df: sorted(tuple(round(v, 9) if isinstance(v, float) else v for v in r) for r in df.collect())
    want = key(estimators.estimate(edges, seeds, "naive", spec=spec("local")))
    calls, own = [], estimators.spread_of_all
    monkeypatch.setattr(estimators, "spread_of_all", lambda *args: calls.append(1) or own(*args))
    assert key(estimators.estimate(edges, seeds, "naive", spec=spec("worlds"))) == want
    assert key(estimators.estimate(edges, seeds, "naive", spec=spec("auto"))) == want
    assert len(calls) == 2
    back = edges.unionByName(edges.limit(1).selectExpr("edge_id + 10000 AS edge_id", "dst AS src", "src AS dst", "p"))
    assert key(estimators.estimate(back, seeds, "naive", spec=spec("auto"))) == key(estimators.estimate(back, seeds, "naive", spec=spec("local")))
    assert len(calls) == 2


def test_a_world_without_live_edges(spark):
    edges = spark.range(100).selectExpr("id AS edge_id", "id AS src", "id + 1 AS dst", "0D AS p")
    out = estimators.estimate(edges, edges.selectExpr("src AS seed"), "naive", spec=SampleSpec(n=3, coin="md5", engine="worlds"))
    assert {tuple(r) for r in out.select("f_hat", "draws", "coins").collect()} == {(0.0, 3, 3)}
    assert out.count() == 100
