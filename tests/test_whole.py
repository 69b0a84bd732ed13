"""Queries that do the whole job, against brute force on small tables."""

import itertools

import numpy as np
import pytest

from spreadlab import catalog
from spreadlab.functions.coins import md5_coin
from spreadlab.sources import graphs as G

SF = "/root/testdata/sf0.001"


def test_knn_compares_all_vectors(spark, tmp_path):
    x = np.random.default_rng(1).normal(size=(90, 8)).astype(np.float32)
    rows = [(i, [float(v) for v in x[i]], None if i == 7 else i if i == 8 else i % 4) for i in range(90)]
    spark.createDataFrame([*rows, (90, None, 1)], "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    s = np.round(x.astype(float) @ x.T.astype(float), 6)
    want = {(i, j) for i in range(90) for j in sorted((j for j in range(90) if j != i), key=lambda j: (-s[i, j], j))[:5]}
    for block in (2000, 20):
        assert {(r.src, r.dst) for r in G.knn(spark, str(tmp_path), block=block).collect()} == want


def test_repost_keeps_lines_of_any_frequency(spark, tmp_path):
    hot, warm = "a line that every document has", "a line that some documents have"
    texts = ["\n".join([hot, *([warm] if i % 3 == 0 else []), f"own {i}"]) for i in range(150)]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {(r.src, r.dst): r.w for r in G.repost(spark, str(tmp_path)).collect()}
    assert got == {(a, b): 1 + (a % 3 == 0 and b % 3 == 0) for a, b in itertools.combinations(range(150), 2)}


def test_repost_edges_in_blocks(spark, tmp_path, monkeypatch):
    """Ids, degrees and closures without a table of edges; pairs counted in small pieces, in one way and the other."""
    rng = np.random.default_rng(5)
    texts = {int(i): "\n".join(f"a line of number {n} that is shared" for n in rng.integers(0, 40, rng.integers(0, 5))) for i in rng.choice(10**6, 120, False) - 500_000}
    spark.createDataFrame([*texts.items(), (None, "a line of number 1 that is shared"), (7, None)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    lines_of = {i: {x for x in t.split("\n") if x} for i, t in texts.items()}
    want = [(a, b, len(lines_of[a] & lines_of[b])) for a, b in itertools.product(sorted(texts), repeat=2) if a < b and lines_of[a] & lines_of[b]]
    lines = G.holders(spark, str(tmp_path))
    for size in (1 << 21, 50):
        monkeypatch.setattr(G, "PAIRS", size)
        got = sorted((r.edge_id, r.src, r.dst, r.w) for r in G.prepare_repost(spark, str(tmp_path)).collect())
        assert got == [(i, *e) for i, e in enumerate(want)]
    some = {a for a, *_ in want[::9]}
    degrees = G.out_degrees(lines)
    part = G.repost_edges(lines, degrees.filter(degrees.src.isin(list(some))))
    assert {tuple(r) for r in part.select("edge_id", "src", "dst", "w").collect()} == {x for x in got if x[1] in some}

    def reach(start, ends):
        after = [(e[ends], e[1 - ends]) for e in want]
        seen, size = {start}, 0
        while len(seen) > size:
            size = len(seen)
            seen |= {b for a, b in after if a in seen}
        return seen

    start = want[len(want) // 3][0]
    down = reach(start, 0)
    assert {r.node for r in G.joined_by_lines(lines, spark.createDataFrame([(start,)], "node long")).collect()} == down
    before = G.joined_by_lines(lines, spark.createDataFrame([(max(down),)], "node long"), forward=False)
    assert {r.node for r in before.collect()} == reach(max(down), 1)
    assert {r.node for r in G.joined_by_lines(lines, spark.createDataFrame([(start,)], "node long"), within=before).collect()} == down & reach(max(down), 1)


def test_region_worlds_of_all_edges(spark):
    e = catalog.region_edges(spark, SF)
    rows, seed = e.orderBy("edge_id").collect(), catalog.region_seed(e)
    assert len(rows) == G.region(spark, SF).count() > 12
    world, pr = np.arange(1 << len(rows)), np.ones(1 << len(rows))
    for i, r in enumerate(rows):
        pr *= np.where(world >> i & 1, r.p, 1 - r.p)
    at = {n: i for i, n in enumerate(sorted({seed, *(n for r in rows for n in (r.src, r.dst))}))}
    reach = np.full(len(world), 1 << at[seed])
    for _ in at:
        for i, r in enumerate(rows):
            reach |= (world >> i & reach >> at[r.src] & 1) << at[r.dst]
    f = sum(reach >> i & 1 for i in range(len(at))) - 1
    got = catalog.exact_region(spark, SF).collect()[0]
    assert got.spread == pytest.approx((pr * f).sum(), abs=1e-8) and got.total_probability == pytest.approx(1)
    assert got.variance == pytest.approx((pr * f * f).sum() - (pr * f).sum() ** 2, abs=1e-8)


@pytest.mark.parametrize("name", ["exact_example", "exact_divide_conquer", "conditional_spread", "worst_case_variance"])
def test_exact_values_follow_the_table(spark, tmp_path, name):
    rows = [(10 * c + p, c, f"{p}-X") for c in range(1, 8) for p in range(1, 6)]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_orderpriority string").write.parquet(f"{tmp_path}/orders.parquet")
    seen = []
    read, G.read = G.read, lambda s, d, table: seen.append(table) or read(s, d, table)
    try:
        got = catalog.QUERIES[name](spark, str(tmp_path)).collect()
    finally:
        G.read = read
    assert seen == ["orders"] and len(got) == {"exact_example": 1, "exact_divide_conquer": 5, "conditional_spread": 20, "worst_case_variance": 7}[name]
    if name == "worst_case_variance":
        assert {(r.n, r.measured, r.formula) for r in got} == {(5, 2940.3, 3062.8125)}


def test_graph_is_collected_in_columns(spark, monkeypatch):
    from spreadlab.plans import estimators

    def refused(*_):
        raise AssertionError("rows become objects on the driver")

    e = spark.createDataFrame([(0, 30, 10, 0.5), (1, 10, 20, 0.25), (2, 10, 5, 1.0)], "edge_id long, src long, dst long, p double")
    for kind in {type(e), *type(e).__mro__[:-1]}:
        for name in ("toPandas", "collect"):
            if name in vars(kind):
                monkeypatch.setattr(kind, name, refused)
    g = estimators.collect_graph(e)
    assert g.nodes.tolist() == [5, 10, 20, 30] and g.start.tolist() == [0, 0, 2, 2, 3]
    assert (g.edge_id.tolist(), g.src.tolist(), g.dst.tolist(), g.p.tolist()) == ([2, 1, 0], [1, 1, 3], [0, 2, 1], [1.0, 0.25, 0.5])


def test_cascade_runs_to_its_end(spark, monkeypatch):
    chain = spark.createDataFrame([(i, i, i + 1, 1, 1.0) for i in range(9)], "edge_id long, src long, dst long, w long, p double")
    monkeypatch.setattr(catalog, "message_edges", lambda *_: chain)
    monkeypatch.setattr(G, "random_seeds", lambda *_: spark.createDataFrame([(0,)], "seed long"))
    got = {(r.draw, r.node, r.step) for r in catalog.cascade_steps(spark, SF).collect()}
    assert got == {(d, n, n) for d in range(16) for n in range(10)}


def test_closed_tree_has_every_seed(spark):
    edges = [(r.src, r.dst) for r in G.hierarchy(spark, SF).collect()]
    p = {e: md5_coin(11, *e) for e in edges}
    below = {}
    for a, b in edges:
        below.setdefault(a, []).append(b)
    spread = lambda n: sum(p[n, m] * (1 + spread(m)) for m in below.get(n, ()))
    got = {r.seed: r.spread for r in catalog.spread_closed_tree(spark, SF).collect()}
    assert set(got) == set(below)
    assert all(got[n] == pytest.approx(spread(n), abs=1e-5) for n in below)


def test_sweeps_take_every_value(spark, monkeypatch):
    seen = []
    one = spark.createDataFrame([(1,)], "r int")
    monkeypatch.setattr(G, "prepare", lambda *_: one)
    monkeypatch.setattr(G, "random_seeds", lambda *_: one)
    monkeypatch.setattr(catalog.workloads, "effect_of_r", lambda e, s, scheme, values, spec: seen.append((scheme, values)) or one)
    monkeypatch.setattr(catalog.workloads, "effect_of_n", lambda e, s, values, reps, coin: seen.append(("n", values)) or one)
    catalog.QUERIES["workload_effect_of_r"](spark, SF)
    catalog.QUERIES["workload_effect_of_n"](spark, SF)
    assert seen == [("cube", [1, 2, 3, 5, 10]), ("staircase", [10, 20, 30, 50, 70]), ("n", [200, 500, 1000, 2000, 5000])]


def test_random_graph_takes_the_first_trials(spark, monkeypatch):
    whole = {(r.src, r.dst) for r in G.er(spark, 40, 10**6).collect()}
    monkeypatch.setattr(G, "TRIALS", 30)
    first = [tuple(r) for r in G.er(spark, 40, 300).select("src", "dst").collect()]
    trials = [(int(md5_coin(3, "src", t) * 40), int(md5_coin(3, "dst", t) * 40)) for t in range(350)]
    want = list(dict.fromkeys(p for p in trials if p[0] != p[1]))[:300]
    assert sorted(first) == sorted(want) and set(first) <= whole


def test_scratch_is_deleted(spark, tmp_path):
    from spreadlab.storage import discard, materialize, scratch_scope, shared_root

    assert "://" in shared_root(spark) or shared_root(spark).startswith("file:")
    with scratch_scope(spark) as made:
        kept, gone = materialize(spark.range(3), "kept"), materialize(spark.range(4), "gone")
        made.remove(kept._scratch)
    assert kept.count() == 3
    with pytest.raises(Exception, match="(?i)not.*exist|PATH_NOT_FOUND|FILE_NOT"):
        spark.read.parquet(gone._scratch).count()
    discard(kept, spark.range(1))
    with pytest.raises(Exception, match="(?i)not.*exist|PATH_NOT_FOUND|FILE_NOT"):
        spark.read.parquet(kept._scratch).count()
