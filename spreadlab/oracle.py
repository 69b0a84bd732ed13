"""DuckDB SQL of the derived graphs, orders, strata and of whole estimator runs with md5 coins."""

from __future__ import annotations

from spreadlab.functions.coins import coin_sql
from spreadlab.sources.graphs import EXAMPLE, OFFSET

_TRADE = f"SELECT l_suppkey AS src, o_custkey + {OFFSET} AS dst, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2"


def _trade_by(col: str) -> str:
    return f"""SELECT a.{col}::BIGINT AS src, b.{col}::BIGINT AS dst, sum(w)::BIGINT AS w FROM ({_TRADE}) t
        JOIN supplier s ON s.s_suppkey = t.src JOIN nation a ON a.n_nationkey = s.s_nationkey
        JOIN customer c ON c.c_custkey + {OFFSET} = t.dst JOIN nation b ON b.n_nationkey = c.c_nationkey
        WHERE a.{col} <> b.{col} GROUP BY 1, 2"""


def er_sql(n: int, m: int, salt: int = 3) -> str:
    ends = ", ".join(f"floor({coin_sql(str(salt), chr(39) + side + chr(39), 't')} * {n})::BIGINT AS {side}" for side in ("src", "dst"))
    return f"""SELECT src, dst, 1::BIGINT AS w FROM (SELECT src, dst, min(t) AS t FROM (SELECT t, {ends} FROM range({int(m * 1.1) + 20}) r(t)) WHERE src <> dst GROUP BY 1, 2 ORDER BY t LIMIT {m})"""


GRAPHS = {
    "message": "SELECT src, dst, count(*) AS w FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events WHERE event_type = 'purchase') WHERE src <> dst GROUP BY 1, 2",
    "message_gap": "SELECT src, dst, count(*) AS w FROM (SELECT user_id AS src, lead(user_id) OVER o AS dst, lead(ts) OVER o AS t2, ts FROM events WINDOW o AS (ORDER BY ts, event_id)) WHERE src <> dst AND epoch_us(t2) - epoch_us(ts) <= 120000000 GROUP BY 1, 2",
    "coorder": "WITH p AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) SELECT a.l_partkey AS src, b.l_partkey AS dst, count(*) AS w FROM p a JOIN p b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(*) >= 2",
    "coorder_full": "WITH p AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) SELECT a.l_partkey AS src, b.l_partkey AS dst, count(*) AS w FROM p a JOIN p b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2",
    "supplier_week": "WITH s AS (SELECT DISTINCT l_suppkey AS s, o_custkey AS c, CAST(o_orderdate AS DATE) AS d FROM lineitem JOIN orders ON l_orderkey = o_orderkey) SELECT a.c AS src, b.c AS dst, count(*) AS w FROM s a JOIN s b ON a.s = b.s AND b.d - a.d BETWEEN 1 AND 7 AND a.c <> b.c GROUP BY 1, 2",
    "trade": _TRADE,
    "nation": _trade_by("n_nationkey"),
    "region": _trade_by("n_regionkey"),
    "priority": "WITH o AS (SELECT DISTINCT o_custkey, left(o_orderpriority, 1)::BIGINT AS p FROM orders) SELECT a.p AS src, b.p AS dst, count(*) AS w FROM o a JOIN o b ON a.o_custkey = b.o_custkey AND a.p < b.p GROUP BY 1, 2",
    "hierarchy": f"SELECT n_regionkey::BIGINT AS src, n_nationkey + 1000::BIGINT AS dst, 1::BIGINT AS w FROM nation UNION ALL SELECT c_nationkey + 1000::BIGINT, c_custkey + {OFFSET}, 1::BIGINT FROM customer",
    "repost": "WITH l AS (SELECT DISTINCT doc_id, trim(line, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line, ' ')) >= 20), f AS (SELECT line FROM l GROUP BY 1 HAVING count(*) >= 2), k AS (SELECT l.* FROM l JOIN f USING (line)) SELECT a.doc_id AS src, b.doc_id AS dst, count(*) AS w FROM k a JOIN k b ON a.line = b.line AND a.doc_id < b.doc_id GROUP BY 1, 2",
    "links": """SELECT page_id AS src, dst, count(*) AS w FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS dst FROM pages) GROUP BY 1, 2""",
    "turns": "WITH c AS (SELECT DISTINCT conv_id, turn FROM conversations) SELECT a.conv_id * 1000 + a.turn AS src, a.conv_id * 1000 + a.turn + 1 AS dst, 1::BIGINT AS w FROM c a JOIN c b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
}

KNN = """WITH e AS (SELECT DISTINCT ON (vec_id) vec_id, embedding::DOUBLE[] AS x FROM embeddings),
    s AS (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_dot_product(a.x, b.x), 6) AS s FROM e a JOIN e b ON a.vec_id <> b.vec_id),
    r AS (SELECT *, row_number() OVER (PARTITION BY src ORDER BY s DESC, dst) AS k FROM s)
    SELECT src, dst, 1::BIGINT AS w, greatest(0.0, least(1.0, s)) AS s FROM r WHERE k <= 5"""

EXAMPLE_SQL = "SELECT * FROM (VALUES " + ", ".join(f"({i}::BIGINT, {a}::BIGINT, {b}::BIGINT, {p}::DOUBLE)" for i, (a, b, p) in enumerate(EXAMPLE)) + ") t(edge_id, src, dst, p)"


def edges_sql(graph: str, mean: float = 2.0) -> str:
    return f"SELECT row_number() OVER (ORDER BY src, dst) - 1 AS edge_id, src, dst, w, 1 - exp(-w / {mean}::DOUBLE) AS p FROM ({GRAPHS[graph]})"


def seeds_sql(edges: str, k: int, salt: int = 5) -> str:
    return f"SELECT seed FROM (SELECT DISTINCT src AS seed FROM {edges}) ORDER BY {coin_sql(str(salt), 'seed')}, seed LIMIT {k}"


def naive_sql(edges: str, seeds: str, n: int, reps: int, salt: int = 7, hops: int | None = None) -> str:
    """CTE text that ends in f(seed, rep, draw, f) of the naive draws (reach by set recursion)."""
    c = coin_sql(str(salt), "r.rep", "r.draw", "e.edge_id")
    return f"""edges AS MATERIALIZED ({edges}), seeds AS MATERIALIZED ({seeds}),
    reach AS (SELECT seed, rep, draw, seed AS node FROM seeds, range({reps}) a(rep), range({n}) b(draw)
              UNION SELECT r.seed, r.rep, r.draw, e.dst FROM reach r JOIN edges e ON e.src = r.node WHERE {c} < e.p),
    f AS (SELECT seed, rep, draw, count(*) - 1 AS f FROM reach GROUP BY 1, 2, 3)"""


def bfs_sql(levels: int = 10) -> str:
    """CTEs over edges and one seed that end in ord(ord, edge_id, src, dst, p) in visiting order."""
    out = ["n0 AS MATERIALIZED (SELECT seed AS node, 0::BIGINT AS nord, 0 AS lev FROM seeds)"]
    for i in range(1, levels + 1):
        out.append(f"""n{i} AS MATERIALIZED (SELECT node, nord, lev FROM n{i - 1} UNION ALL
        SELECT node, row_number() OVER (ORDER BY po, node) + (SELECT max(nord) FROM n{i - 1}), {i} FROM
        (SELECT e.dst AS node, min(n.nord) AS po FROM edges e JOIN n{i - 1} n ON n.node = e.src AND n.lev = {i - 1}
         WHERE e.dst NOT IN (SELECT node FROM n{i - 1}) GROUP BY 1))""")
    out.append(f"ord AS MATERIALIZED (SELECT row_number() OVER (ORDER BY nord, dst) - 1 AS ord, edge_id, src, dst, p FROM edges JOIN n{levels} ON node = src)")
    return ", ".join(out)


def steps_sql(live: str, seeds: str, draws: int) -> str:
    """CTE text that ends in d(draw, node, step): the cascade's steps in live(draw, src, dst), each node once, to its end."""
    return f"""live AS MATERIALIZED ({live}),
    d(draw, node, step) USING KEY (draw, node) AS (SELECT draw, seed, 0 FROM ({seeds}), range({draws}) r(draw)
        UNION SELECT d.draw, l.dst, any_value(d.step) + 1 FROM d JOIN live l ON l.draw = d.draw AND l.src = d.node LEFT JOIN recurring.d k ON k.draw = l.draw AND k.node = l.dst WHERE k.node IS NULL GROUP BY 1, 2)"""


def strata_sql(scheme: str, r: int, cursors: str, keys: str = "") -> str:
    """CTEs over ord(.., ord, edge_id, p) that end in strata(.., cursor, child, pi, lo, hi, consumed, status)."""
    k, g = (f"{keys}, ", f"{keys}, ") if keys else ("", "")
    if scheme == "cube":
        kids = f"SELECT c::INTEGER AS child, {r} AS consumed FROM range({1 << r}) t(c)"
        live, used = "((child >> j::INTEGER) & 1) = 1", "true"
        status = f"list_transform(range({r}), lambda j: (child >> j::INTEGER) & 1)"
    else:
        kids = f"SELECT c::INTEGER AS child, CASE WHEN c = 0 THEN {r} ELSE c END::INTEGER AS consumed FROM range({r + 1}) t(c)"
        live, used = "child = j + 1", "j < consumed"
        status = "list_transform(range(consumed), lambda j: CASE WHEN child = j + 1 THEN 1 ELSE 0 END)"
    return f"""sel AS (SELECT {k}cursor, ord - cursor AS j, p FROM ord, ({cursors}) c(cursor) WHERE ord >= cursor AND ord < cursor + {r}),
    kids AS ({kids}),
    mass AS (SELECT {k}cursor, child, any_value(consumed) AS consumed, product(CASE WHEN NOT ({used}) THEN 1.0 WHEN {live} THEN p ELSE 1 - p END) AS pi
             FROM sel, kids GROUP BY {g}cursor, child HAVING count(*) = {r}),
    cum AS (SELECT *, sum(pi) OVER (PARTITION BY {g}cursor ORDER BY child) AS top, row_number() OVER (PARTITION BY {g}cursor ORDER BY child DESC) AS back FROM mass WHERE pi > 0),
    strata AS MATERIALIZED (SELECT {k}cursor, child, pi, lag(CASE WHEN back = 1 THEN 2.0 ELSE top END, 1, 0.0) OVER (PARTITION BY {g}cursor ORDER BY child) AS lo,
             CASE WHEN back = 1 THEN 2.0 ELSE top END AS hi, consumed, {status} AS status FROM cum)"""


def estimator_sql(edges: str, seeds: str, scheme: str, selector: str, r: int, recursive: bool, n: int, reps: int, tau: int = 10, salt: int = 7, most_cursor: int = 400, levels: int = 10, draws: bool = False) -> str:
    """(seed, rep, f_hat) of a stratified estimator: one recursion for the tree, one for the reach; draws: each one's outcome, path and coins."""
    if selector == "bfs":
        order, keys, on_rep, on_rep2 = bfs_sql(levels), "", "", ""
    else:
        order = f"ord AS MATERIALIZED (SELECT rep, row_number() OVER (PARTITION BY rep ORDER BY {coin_sql(str(salt), chr(39) + 'order' + chr(39), 'rep', 'edge_id')}, edge_id) - 1 AS ord, edge_id, src, dst, p FROM edges, range({reps}) a(rep))"
        keys, on_rep, on_rep2 = "rep", "AND s.rep = t.rep", "AND o.rep = x.rep"
    step = r if scheme == "cube" else 1
    grown = strata_sql(scheme, r, f"SELECT unnest(range(0, {most_cursor if recursive else 1}, {step}))", keys)
    slot = f"((t.k + {coin_sql(str(salt), 't.rep', 't.path', 't.k')}) / t.n)"
    leaf = (f"n2 < {tau} OR " if recursive else "true OR ") + f"(SELECT max(ord) + 1 FROM ord) - cursor2 < {r}"
    first = ("" if not recursive else f"{n} < {tau} OR ") + f"(SELECT max(ord) + 1 FROM ord) < {r}"
    c = coin_sql(str(salt), "x.rep", "x.draw", "o.edge_id")
    result = "SELECT (SELECT seed FROM seeds) AS seed, rep::INTEGER AS rep, round(avg(f), 9) AS f_hat FROM (SELECT rep, draw, count(*) - 1 AS f FROM x GROUP BY 1, 2) GROUP BY 1, 2"
    if draws:
        result = f""", thrown AS (SELECT x.rep, x.draw, count(*) AS coins FROM x JOIN leaf l ON l.rep = x.rep AND l.draw = x.draw JOIN ord o ON o.src = x.node {on_rep2} WHERE o.ord >= l.cursor GROUP BY 1, 2)
    SELECT (SELECT seed FROM seeds) AS seed, l.rep, l.draw, l.path, count(*) - 1 AS f, coalesce(any_value(t.coins), 0) AS coins FROM x JOIN leaf l ON l.rep = x.rep AND l.draw = x.draw LEFT JOIN thrown t ON t.rep = x.rep AND t.draw = x.draw GROUP BY ALL"""
    return f"""WITH RECURSIVE edges AS MATERIALIZED ({edges}), seeds AS MATERIALIZED ({seeds}), {order}, {grown},
    t AS (SELECT rep, draw, '' AS path, 0::BIGINT AS cursor, draw AS k, {n}::BIGINT AS n, []::INTEGER[] AS fixed, ({first}) AS done FROM range({reps}) a(rep), range({n}) b(draw)
        UNION ALL SELECT rep, draw, path2, cursor2, k2, n2, fixed2, ({leaf}) FROM (
            SELECT *, row_number() OVER (PARTITION BY rep, path2 ORDER BY draw) - 1 AS k2, count(*) OVER (PARTITION BY rep, path2) AS n2 FROM (
                SELECT t.rep, t.draw, t.path || '.' || s.child AS path2, t.cursor + s.consumed AS cursor2, list_concat(t.fixed, s.status::INTEGER[]) AS fixed2
                FROM t JOIN strata s ON s.cursor = t.cursor AND {slot} >= s.lo AND {slot} < s.hi {on_rep} WHERE NOT t.done))),
    leaf AS MATERIALIZED (SELECT * FROM t WHERE done),
    x AS (SELECT l.rep, l.draw, seed AS node FROM leaf l, seeds
        UNION SELECT x.rep, x.draw, o.dst FROM x JOIN leaf l ON l.rep = x.rep AND l.draw = x.draw JOIN ord o ON o.src = x.node {on_rep2}
        WHERE CASE WHEN o.ord < l.cursor THEN l.fixed[o.ord + 1] = 1 ELSE {c} < o.p END)
    {result}"""


def worlds_sql(edges: str, seed: int | str, m: int, fixed: str = "true") -> str:
    """CTE text that ends in w(world, pr, f) over all worlds of a micro graph (positions i in edge_id order)."""
    return f"""edges AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY edge_id) - 1 AS i FROM ({edges})), ids AS (SELECT world FROM range({1 << m}) t(world) WHERE {fixed}),
    prob AS (SELECT world, product(CASE WHEN (world >> i::INTEGER) & 1 = 1 THEN p ELSE 1 - p END) AS pr FROM ids, edges GROUP BY 1),
    reach AS (SELECT world, {seed}::BIGINT AS node FROM ids UNION SELECT r.world, e.dst FROM reach r JOIN edges e ON e.src = r.node AND (r.world >> e.i::INTEGER) & 1 = 1),
    w AS (SELECT world, pr, count(*) - 1 AS f FROM reach JOIN prob USING (world) GROUP BY 1, 2)"""


def estimates_sql(edges: str, k: int, methods: dict[str, tuple], n: int, reps: int, **options) -> str:
    """(estimator, seed, rep, f_hat) of several estimators over k random seeds; methods: name -> (scheme, selector, recursive, r)."""
    parts = []
    for method, (scheme, selector, recursive, r) in methods.items():
        if scheme is None:
            parts.append(f"SELECT '{method}' AS estimator, seed, rep, f_hat FROM (WITH RECURSIVE {naive_sql(edges, seeds_sql('edges', k), n, reps)} SELECT seed, rep, avg(f) AS f_hat FROM f GROUP BY 1, 2)")
            continue
        for i in range(k):
            one = f"SELECT seed FROM ({seeds_sql('edges', i + 1)}) OFFSET {i}"
            parts.append(f"SELECT '{method}' AS estimator, seed, rep, f_hat FROM ({estimator_sql(edges, one, scheme, selector, r, recursive, n, reps, **options)})")
    return " UNION ALL ".join(parts)


def relative_sql(estimates: str, base: str = "naive") -> str:
    """CTE text that ends in rel(estimator, mean_of_ratios, ratio_of_means, seeds, excluded)."""
    return f"""e AS MATERIALIZED ({estimates}), v AS (SELECT estimator, seed, var_samp(f_hat) AS v FROM e GROUP BY 1, 2),
    rel AS (SELECT a.estimator, avg(CASE WHEN b.v > 0 THEN a.v / b.v END) AS mean_of_ratios, CASE WHEN sum(b.v) > 0 THEN sum(a.v) / sum(b.v) END AS ratio_of_means, count(CASE WHEN b.v > 0 THEN 1 END) AS seeds, count(CASE WHEN b.v > 0 THEN NULL ELSE 1 END) AS excluded
            FROM v a JOIN v b ON a.seed = b.seed AND b.estimator = '{base}' GROUP BY 1)"""
