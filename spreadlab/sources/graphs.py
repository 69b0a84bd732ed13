"""Influence graphs derived from the given tables: edges(src, dst, w), no loops, one row per pair.

Defined cases, for every builder: a null end makes no edge and a null text, list or time no row; repeated
rows add to the weight, but for orders' parts, lines of a document and turns, which count once; ties of a
time go by the event's id, ties of a similarity to the smaller id; lines and texts are read whole; an empty
table gives an empty graph; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadlab.functions.coins import coin, key_of, mixed_coins
from spreadlab.storage import materialize

TRIALS = 100_000  # of a range of trials of a random graph
PAIRS = 1 << 21  # of documents, parts or customers that are counted at a time
TASK_ROWS = 500_000  # of lines in a task that makes pairs of them
OFFSET = 1_000_000_000  # customers' ids in graphs that also hold suppliers
EXAMPLE = ((5, 3, 0.6), (5, 6, 0.3), (3, 1, 0.5), (3, 4, 0.4), (6, 2, 0.7), (1, 2, 0.2), (1, 3, 0.3), (1, 4, 0.5), (4, 6, 0.6), (2, 6, 0.4))


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def weighted(pairs: DataFrame) -> DataFrame:
    """One row per (src, dst) with its count; loops are dropped."""
    return pairs.filter("src <> dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("w"))


def sorted_runs(df: DataFrame, *order: str) -> tuple[DataFrame, DataFrame]:
    """Range-partitioned, sorted rows with (pid, nth), and the count of each partition.

    Written once, so that positions do not change between the two uses.
    """
    placed = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("pid", F.spark_partition_id()).withColumn("nth", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1))
    rows = materialize(placed, "sorted")
    return rows, rows.groupBy("pid").agg(F.count(F.lit(1)).alias("rows"))


def with_edge_ids(edges: DataFrame) -> DataFrame:
    """Dense edge_id in (src, dst) order; only one count per partition meets in a single task."""
    if (placed := getattr(edges, "_placed", None)) is not None:  # in order already
        rows = materialize(placed, "sorted")
        counts = rows.groupBy("pid").agg(F.count(F.lit(1)).alias("rows"))
    else:
        rows, counts = sorted_runs(edges, "src", "dst")
    base = counts.withColumn("base", F.sum("rows").over(Window.orderBy("pid")) - F.col("rows")).drop("rows")
    return rows.join(F.broadcast(base), "pid").withColumn("edge_id", F.col("base") + F.col("nth")).drop("pid", "nth", "base")


def tally(a: np.ndarray, b: np.ndarray, w: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct pairs (a, b) in order, and how often each is there, or the sum of its w."""
    if not len(a):
        return a, b, np.zeros(0, np.int64)
    low = int(a.min()), int(b.min())
    spans = int(a.max()) - low[0] + 1, int(b.max()) - low[1] + 1
    if spans[0] * spans[1] >= 1 << 63:  # ranks make smaller keys
        (a, i), (b, j) = (np.unique(x, return_inverse=True) for x in (a, b))
        i, j, n = tally(i, j, w)
        return a[i], b[j], n
    key = (a - low[0]) * spans[1] + (b - low[1])
    if w is None:
        key = np.sort(key)
    else:
        order = np.argsort(key, kind="stable")
        key, w = key[order], w[order]
    heads = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    n = np.diff(np.append(heads, len(key))) if w is None else np.add.reduceat(w, heads)
    key = key[heads]
    first = key // spans[1]
    return first + low[0], key - first * spans[1] + low[1], n


def whole(batches: Iterator[pa.RecordBatch], columns: int) -> list[np.ndarray]:
    """All rows of a partition by column; none is null."""
    some = [[b.column(i).to_numpy(zero_copy_only=False) for i in range(columns)] for b in batches]
    return [np.concatenate(x) for x in zip(*some, strict=True)] if some else [np.zeros(0, np.int64)] * columns


def spread_out(starts: np.ndarray, lengths: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row, position) of every position in each row's range, some PAIRS of them at a time."""
    until = np.cumsum(lengths)
    at = 0
    while at < len(lengths):
        done = until[at] - lengths[at]
        end = max(at + 1, int(np.searchsorted(until, done + PAIRS, "right")))
        n = lengths[at:end]
        yield np.repeat(np.arange(at, end), n), np.repeat(starts[at:end] - (until[at:end] - n - done), n) + np.arange(int(n.sum()))
        at = end


def tasks_for(df: DataFrame) -> int:
    """Tasks that the rows of ``df`` are dealt to."""
    return max(df.sparkSession.sparkContext.defaultParallelism, -(-df.count() // TASK_ROWS))


def cuts_of(df: DataFrame, column: str, parts: int) -> np.ndarray:
    """Values that split a column in about so many equal parts."""
    return np.unique(np.array(df.approxQuantile(column, [i / parts for i in range(1, parts)], 0.25 / parts) if parts > 1 else [], np.float64).astype(np.int64))


def dealt_pairs(src: np.ndarray, dst: np.ndarray, cuts: np.ndarray) -> pa.RecordBatch:
    """(block, pairs): the counted pairs of each range of src, packed."""
    src, dst, w = tally(src, dst)
    block = np.searchsorted(cuts, src, "right")
    heads = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]])) if len(block) else block
    parts = [np.stack([x[i:j] for x in (src, dst, w)]).tobytes() for i, j in zip(heads, [*heads[1:], len(block)], strict=True)] if len(block) else []
    return pa.RecordBatch.from_arrays([pa.array(block[heads].astype(np.int32)), pa.array(parts, pa.binary())], ["block", "pairs"])


def counted_pairs(dealt: DataFrame, parts: int, least: int = 1) -> DataFrame:
    """As ``weighted`` of dealt(block, pairs), with at least so many of each, in order: ``with_edge_ids`` needs no sort of it."""
    schema = pa.schema([("pid", pa.int32()), *((n, pa.int64()) for n in ("nth", "src", "dst", "w"))])

    def count(block: int, packed: list[bytes]) -> Iterator[pa.RecordBatch]:
        src, dst, w = tally(*np.concatenate([np.frombuffer(x, np.int64).reshape(3, -1) for x in packed], axis=1))
        some = (w >= least) & (src != dst)
        columns = [np.arange(int(some.sum())), src[some], dst[some], w[some]]
        for i in range(0, len(columns[0]), 1 << 16):
            part = [c[i : i + (1 << 16)] for c in columns]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part[0]), block, np.int32)), *map(pa.array, part)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, packed = None, []
        for b in batches:
            for block, pairs in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if block != current:
                    if packed:
                        yield from count(current, packed)
                    current, packed = block, []
                packed.append(pairs)
        if packed:
            yield from count(current, packed)

    placed = dealt.repartition(parts, "block").sortWithinPartitions("block").mapInArrow(run, "pid int, nth long, src long, dst long, w long")
    out = placed.select("src", "dst", "w")
    out._placed = placed
    return out


def successor(df: DataFrame, value: str, *order: str) -> DataFrame:
    """df + next_<c> of value and the first order column, in global order, without a global window.

    A range partition finds successors within itself; its last row takes the next partition's first.
    """
    rows, _ = sorted_runs(df, *order)
    near = Window.partitionBy("pid").orderBy("nth")
    firsts = rows.filter("nth = 0").select("pid", F.struct(value, order[0]).alias("head"))
    follow = firsts.select("pid", F.lead("head").over(Window.orderBy("pid")).alias("after"))
    met = rows.withColumn("inside", F.lead(F.struct(value, order[0])).over(near)).join(follow, "pid")
    got = F.coalesce("inside", "after")
    return met.select(*df.columns, got[value].alias(f"next_{value}"), got[order[0]].alias(f"next_{order[0]}"))


def example(spark: SparkSession) -> DataFrame:
    """Six-node worked example with its probabilities; edge_id is the visiting order from node 5."""
    return spark.createDataFrame([(i, a, b, p) for i, (a, b, p) in enumerate(EXAMPLE)], "edge_id long, src long, dst long, p double")


def message(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User -> user of the next purchase."""
    e = read(spark, sf_dir, "events").filter("event_type = 'purchase'").select("user_id", "ts", "event_id")
    return weighted(successor(e, "user_id", "ts", "event_id").filter("next_user_id IS NOT NULL").select(F.col("user_id").alias("src"), F.col("next_user_id").alias("dst")))


def message_gap(spark: SparkSession, sf_dir: str, minutes: int = 2) -> DataFrame:
    """User -> user of the next event of any kind within some minutes."""
    e = read(spark, sf_dir, "events").select("user_id", "ts", "event_id")
    near = successor(e, "user_id", "ts", "event_id").filter(F.unix_micros(F.col("next_ts").cast("timestamp")) - F.unix_micros(F.col("ts").cast("timestamp")) <= minutes * 60_000_000)
    return weighted(near.select(F.col("user_id").alias("src"), F.col("next_user_id").alias("dst")))


def coorder(spark: SparkSession, sf_dir: str, least: int = 2) -> DataFrame:
    """Parts on the same order."""
    p = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").cast("long").alias("o"), F.col("l_partkey").cast("long").alias("p")).dropna()
    parts = tasks_for(p)
    cuts = cuts_of(p, "p", parts)

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order, part, _ = tally(*whole(batches, 2))
        more = np.searchsorted(order, order, "right") - np.arange(len(order)) - 1  # later parts of the order
        for row, other in spread_out(np.arange(len(order)) + 1, more):
            yield dealt_pairs(part[row], part[other], cuts)

    return counted_pairs(p.repartition(parts, "o").mapInArrow(pairs, "block int, pairs binary"), parts, least)


def supplier_week(spark: SparkSession, sf_dir: str, days: int = 7) -> DataFrame:
    """Customers of one supplier 1 to ``days`` days apart, earlier -> later; rows are dealt by supplier and span of days."""
    o = read(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("long").alias("k"), F.col("o_custkey").cast("long").alias("c"), F.datediff(F.to_date("o_orderdate"), F.lit("1970-01-01")).cast("long").alias("day")).dropna()
    li = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").cast("long").alias("k"), F.col("l_suppkey").cast("long").alias("s")).dropna()
    parts = tasks_for(li)
    cuts = cuts_of(o, "c", parts)

    def sold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """(block, rows): supplier, customer, day and whether it may be the later one, packed."""
        key, x, day, kind = whole(batches, 4)
        by_key = np.argsort(key[kind == 0], kind="stable")
        ok, oc, od = (v[kind == 0][by_key] for v in (key, x, day))
        lk, ls = key[kind == 1], x[kind == 1]
        low = np.searchsorted(ok, lk)
        for row, at in spread_out(low, np.searchsorted(ok, lk, "right") - low):
            s, c, d = ls[row], oc[at], od[at]
            week = d // days
            s, c, d, week, late = (np.concatenate(v) for v in ((s, s), (c, c), (d, d), (week, week + 1), (np.ones_like(s), np.zeros_like(s))))
            block = (mixed_coins(key_of("block"), s * 1_000_003 + week) * parts).astype(np.int64)
            order = np.argsort(block, kind="stable")
            rows = np.stack([s, week, c, d, late])[:, order]
            edge = np.searchsorted(block[order], np.arange(parts + 1))
            some = np.flatnonzero(edge[1:] > edge[:-1])
            yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array([rows[:, edge[i] : edge[i + 1]].tobytes() for i in some.tolist()], pa.binary())], ["block", "rows"])

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packed = [np.frombuffer(x, np.int64).reshape(5, -1) for b in batches for x in b.column(1).to_pylist()]
        if not packed:
            return
        s, week, c, d, late = np.concatenate(packed, axis=1)
        _, group = np.unique(s, return_inverse=True)
        first = int(week.min())
        group = group * (int(week.max()) - first + 1) + week - first  # supplier and week
        low = int(d.min())
        span = int(d.max()) - low + days + 2
        when, c, _ = tally(group * span + d - low, 2 * c + late)
        c, is_late = c >> 1, (c & 1).astype(bool)
        # earlier rows are all of a group, later ones those of its own week
        at, ends = when[is_late], c[is_late]
        start = np.searchsorted(at, when + 1)
        for row, other in spread_out(start, np.searchsorted(at, when + days, "right") - start):
            yield dealt_pairs(c[row], ends[other], cuts)

    none = F.lit(0).cast("long")
    both = o.select("k", F.col("c").alias("x"), "day", F.lit(0).alias("kind")).unionByName(li.select("k", F.col("s").alias("x"), none.alias("day"), F.lit(1).alias("kind")))
    dealt = both.repartition(parts, "k").mapInArrow(sold, "block int, rows binary").repartition(parts, "block")
    return counted_pairs(dealt.mapInArrow(pairs, "block int, pairs binary"), parts)


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supplier -> customer, w = lines."""
    o = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    li = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_suppkey")
    return weighted(li.join(o, "o_orderkey").select(F.col("l_suppkey").alias("src"), (F.col("o_custkey") + OFFSET).alias("dst")))


def _trade_by(spark: SparkSession, sf_dir: str, level: str) -> DataFrame:
    n = read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("n"), F.col("n_regionkey" if level == "region" else "n_nationkey").cast("long").alias("g"))
    s = read(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("src"), F.col("s_nationkey").cast("long").alias("n")).join(n, "n").select("src", F.col("g").alias("sg"))
    c = read(spark, sf_dir, "customer").select((F.col("c_custkey") + OFFSET).alias("dst"), F.col("c_nationkey").cast("long").alias("n")).join(n, "n").select("dst", F.col("g").alias("cg"))
    t = trade(spark, sf_dir).join(s, "src").join(c, "dst").filter("sg <> cg")
    return t.groupBy(F.col("sg").alias("src"), F.col("cg").alias("dst")).agg(F.sum("w").alias("w"))


def nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trade from nation to nation."""
    return _trade_by(spark, sf_dir, "nation")


def region(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trade from region to region."""
    return _trade_by(spark, sf_dir, "region")


def priority(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order priorities of one customer, more urgent -> less, w = customers."""
    o = read(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c"), F.substring("o_orderpriority", 1, 1).cast("long").alias("p")).distinct()
    return weighted(o.select("c", F.col("p").alias("src")).join(o.select("c", F.col("p").alias("dst")), "c").filter("src < dst"))


def hierarchy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Region -> nation -> customer tree (ids offset by level)."""
    n = read(spark, sf_dir, "nation").select(F.col("n_regionkey").cast("long").alias("src"), (F.col("n_nationkey") + 1000).cast("long").alias("dst"))
    c = read(spark, sf_dir, "customer").select((F.col("c_nationkey") + 1000).cast("long").alias("src"), (F.col("c_custkey") + OFFSET).alias("dst"))
    return weighted(n.unionByName(c))


def repost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that share a line (20 characters or more), lower id -> higher, in (src, dst) order within a partition."""
    return shared_pairs(holders(spark, sf_dir)).select("src", "dst", "w")


def prepare_repost(spark: SparkSession, sf_dir: str, mean: float = 2.0) -> DataFrame:
    """As ``prepare`` of ``repost``, without a sort of its edges."""
    lines = holders(spark, sf_dir)
    return materialize(repost_edges(lines, out_degrees(lines), mean), "edges")


def holders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(line, docs): a number for every line that two documents or more hold, and their ids in order; lines travel as their SHA-256."""
    lines = read(spark, sf_dir, "documents").filter("doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc"), F.explode(F.split("text", "\n")).alias("line"))
    lines = lines.select("doc", F.trim("line").alias("line")).filter("length(line) >= 20").select("doc", F.unhex(F.sha2("line", 256)).alias("line"))
    return materialize(lines.groupBy("line").agg(F.array_sort(F.collect_set("doc")).alias("docs")).filter("size(docs) > 1").select(F.monotonically_increasing_id().alias("line"), "docs"), "holders")


def out_degrees(lines: DataFrame) -> DataFrame:
    """(src, base, out): edges from each document of ``holders``, and those of all smaller ones, which is the least edge_id."""
    found = materialize(shared_pairs(lines, count=True), "degrees")
    before = found.groupBy("block").agg(F.sum("out").alias("rows")).withColumn("above", F.sum("rows").over(Window.orderBy("block")) - F.col("rows")).drop("rows")
    return found.join(F.broadcast(before), "block").select("src", (F.col("above") + F.col("nth")).alias("base"), "out")


def repost_edges(lines: DataFrame, degrees: DataFrame, mean: float = 2.0) -> DataFrame:
    """edges(edge_id, src, dst, w, p) from the documents in ``degrees``: none are written, and those of others are not made."""
    return exponential(shared_pairs(lines, degrees.filter("out > 0")), mean).select(F.col("nth").alias("edge_id"), "src", "dst", "w", "p")


def shared_pairs(lines: DataFrame, wanted: DataFrame | None = None, count: bool = False) -> DataFrame:
    """(block, nth, src, dst, w) of lines(docs) in (src, dst) order, or with ``count`` (block, nth, src, out); no pair is shuffled.

    Documents are dealt in blocks of neighbouring ids; a line goes once to each block that has a holder,
    without the holders before it. nth counts the block's earlier pairs, or from base where
    wanted(src, base) names the documents whose pairs are made.
    """
    spark = lines.sparkSession
    blocks = 4 * max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    docs = lines.select(F.explode("docs").alias("doc"))
    cuts = sorted({int(x) for x in docs.approxQuantile("doc", [i / blocks for i in range(1, blocks)], 0.1 / blocks)}) if not lines.isEmpty() else []
    block_of = lambda x: F.array_size(F.filter(F.array(*(F.lit(c).cast("long") for c in cuts)).cast("array<long>"), lambda c: c <= x))
    none = F.lit(None).cast("array<long>")
    dealt = lines.withColumn("block", F.explode(F.array_distinct(F.transform("docs", block_of))))
    low = F.get(F.array(*(F.lit(c).cast("long") for c in [-(1 << 63), *cuts])), F.col("block"))
    rows = dealt.select("block", F.filter("docs", lambda x: x >= low).alias("docs"), none.alias("bases"))
    if wanted is not None:
        named = wanted.select(block_of(F.col("src")).alias("block"), F.struct("src", "base").alias("x")).groupBy("block").agg(F.array_sort(F.collect_list("x")).alias("x"))
        rows = rows.unionByName(named.select("block", F.col("x.src").alias("docs"), F.col("x.base").alias("bases")))
    schema = pa.schema([(n, pa.int32() if n == "block" else pa.int64()) for n in ("block", "nth", "src", *(("out",) if count else ("dst", "w")))])

    def pairs(block: int, some: list[np.ndarray], named: tuple[np.ndarray, np.ndarray] | None) -> Iterator[pa.RecordBatch]:
        if not some:
            return
        flat = np.concatenate(some)
        stop = np.repeat(np.cumsum([len(x) for x in some]), [len(x) for x in some])
        ids, at = np.unique(flat, return_inverse=True)
        own = np.flatnonzero(flat < cuts[block]) if block < len(cuts) else np.arange(len(flat))
        own = own[np.isin(flat[own], named[0])] if named is not None else own
        own = own[np.argsort(at[own], kind="stable")]
        more = stop[own] - own - 1  # later holders of the line
        heads = np.flatnonzero(np.concatenate([[True], at[own][1:] != at[own][:-1]])) if len(own) else own
        met = np.concatenate([np.add.reduceat(more, heads) if len(own) else more, [0]])
        nth, first = 0, 0
        while first < len(heads):
            last, size = first + 1, met[first]
            while last < len(heads) and size + met[last] <= PAIRS:
                size, last = size + met[last], last + 1
            a, z = heads[first], heads[last] if last < len(heads) else len(own)
            n = more[a:z]
            who = np.repeat(np.repeat(np.arange(last - first), np.diff([*heads[first:last], z])), n)
            other = at[np.repeat(own[a:z] + 1, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)]
            key = who * len(ids) + other
            if (last - first) * len(ids) <= 4 * len(key):
                w = np.bincount(key, minlength=(last - first) * len(ids))
                key = np.flatnonzero(w)
                w = w[key]
            else:
                key, w = np.unique(key, return_counts=True)
            who, src = key // len(ids), ids[at[own[heads[first:last]]]]
            out = np.bincount(who, minlength=last - first)
            before = np.cumsum(out) - out
            if count:
                columns = [nth + before, src, out]
            else:
                base = nth + before if named is None else named[1][np.searchsorted(named[0], src)]
                columns = [base[who] + np.arange(len(who)) - before[who], src[who], ids[key % len(ids)], w]
            nth, first = nth + int(out.sum()), last
            for i in range(0, len(columns[0]), 1 << 16):
                part = [c[i : i + (1 << 16)] for c in columns]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part[0]), block, np.int32)), *(pa.array(c.astype(np.int64)) for c in part)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, some, named = None, [], None
        done = lambda: () if current is None or wanted_only and named is None else pairs(current, some, named)
        for b in batches:
            for block, docs, bases in zip(b.column(0).to_pylist(), b.column(1), b.column(2), strict=True):
                if block != current:
                    yield from done()
                    current, some, named = block, [], None
                ids = docs.values.to_numpy()
                if bases.is_valid:
                    named = ids, bases.values.to_numpy()
                else:
                    some.append(ids)
        yield from done()

    wanted_only = wanted is not None
    return rows.repartition(blocks, "block").sortWithinPartitions("block").mapInArrow(run, ", ".join(f"{f.name} {'int' if f.name == 'block' else 'long'}" for f in schema))


def joined_by_lines(lines: DataFrame, nodes: DataFrame, forward: bool = True, within: DataFrame | None = None) -> DataFrame:
    """(node): the nodes and all that they reach along ``repost`` edges, or that reach them; ``within``: by way of these only."""
    held = lines.select("line", F.explode("docs").alias("node"))
    held = materialize(held if within is None else held.join(within, "node", "left_semi"), "held-lines")
    front = seen = materialize(nodes.select(F.col("node").cast("long").alias("node")).distinct(), "joined")
    while not front.isEmpty():
        best = held.join(front, "node").groupBy("line").agg((F.min if forward else F.max)("node").alias("end"))
        new = held.join(best, "line").filter(F.col("node") > F.col("end") if forward else F.col("node") < F.col("end")).select("node").distinct().join(seen, "node", "left_anti")
        front = materialize(new, "joined")
        seen = materialize(seen.unionByName(front), "joined")
    return seen


def knn(spark: SparkSession, sf_dir: str, k: int = 5, block: int = 2000) -> DataFrame:
    """The k nearest of all other vectors by inner product, with s = clipped similarity and w = 1.

    Every pair of blocks is one matrix product that keeps k rows a vector. Shorter vectors count as
    filled up with zeros; null, empty and non-finite ones take no part; a repeated id is one vector.
    """
    e = read(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("v"), F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    e = e.filter("v IS NOT NULL AND size(x) > 0").filter(F.forall("x", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))).dropDuplicates(["v"])
    e = materialize(e, "vectors")
    blocks = max(1, -(-e.count() // block))
    every = F.sequence(F.lit(0), F.lit(blocks - 1))
    dealt = e.withColumn("own", F.pmod(F.xxhash64("v"), F.lit(blocks)).cast("int"))
    left = dealt.withColumn("other", F.explode(every))
    right = dealt.withColumnRenamed("own", "other").withColumn("own", F.explode(every))

    def nearest(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"src": [], "dst": [], "s": []})
        b = b.sort_values("v")
        width = max(map(len, [*a["x"], *b["x"]]))
        x, y = (np.stack([np.pad(np.asarray(v, float), (0, width - len(v))) for v in side["x"]]) for side in (a, b))
        src, dst = a["v"].to_numpy(), b["v"].to_numpy()
        out = []
        for at in range(0, len(src), 256):
            s = np.round(x[at : at + 256] @ y.T, 6)
            s[src[at : at + 256, None] == dst] = -np.inf
            best = np.argsort(-s, axis=1, kind="stable")[:, :k]
            out.append(pd.DataFrame({"src": np.repeat(src[at : at + 256], best.shape[1]), "dst": dst[best].ravel(), "s": np.take_along_axis(s, best, 1).ravel()}))
        near = pd.concat(out)
        return near[near["src"] != near["dst"]]

    dots = left.groupBy("own", "other").cogroup(right.groupBy("own", "other")).applyInPandas(nearest, "src long, dst long, s double")
    best = dots.withColumn("rank", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("s"), "dst"))).filter(F.col("rank") <= k)
    return best.select("src", "dst", F.lit(1).cast("long").alias("w"), F.greatest(F.lit(0.0), F.least(F.lit(1.0), "s")).alias("s"))


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page -> href target as text."""
    hrefs = read(spark, sf_dir, "pages").select(F.col("page_id").alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("dst"))
    return hrefs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("w"))


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turn -> next turn of a conversation (id = conv_id * 1000 + turn)."""
    c = read(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    after = c.select("conv_id", (F.col("turn") - 1).alias("turn"))
    return weighted(c.join(after, ["conv_id", "turn"]).select((F.col("conv_id") * 1000 + F.col("turn")).alias("src"), (F.col("conv_id") * 1000 + F.col("turn") + 1).alias("dst")))


def er(spark: SparkSession, n: int, m: int, salt: int = 3, kind: str = "md5") -> DataFrame:
    """Random directed graph: hashed end points of enough trials, the first m distinct pairs by trial."""
    trials = spark.range(int(m * 1.1) + 20).withColumnRenamed("id", "t")
    ends = trials.select("t", *(F.floor(coin(salt, side, F.col("t"), kind=kind) * n).cast("long").alias(side) for side in ("src", "dst")))
    pairs = materialize(ends.filter("src <> dst").groupBy("src", "dst").agg(F.min("t").alias("t")), "trials")
    # the m-th trial that counts lies in one range of trials, found from the ranges' counts; only that range is ordered
    ranges = pairs.groupBy(F.floor(F.col("t") / TRIALS).alias("range")).agg(F.count(F.lit(1)).alias("rows"))
    total = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, 0)
    cut = ranges.withColumn("until", F.sum("rows").over(total)).filter(F.col("until") >= m).orderBy("range").limit(1).collect()
    if cut:
        nth = m - (cut[0].until - cut[0].rows)
        last = pairs.filter(F.floor(F.col("t") / TRIALS) == cut[0].range).orderBy("t").limit(nth).agg(F.max("t")).collect()[0][0]
        pairs = pairs.filter(F.col("t") <= last)
    return pairs.select("src", "dst", F.lit(1).cast("long").alias("w"))


def symmetrize(edges: DataFrame) -> DataFrame:
    """Each undirected pair as two arcs with coins of their own; equal arcs are added up."""
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    return edges.select("src", "dst", "w").unionByName(back).groupBy("src", "dst").agg(F.sum("w").alias("w"))


def exponential(edges: DataFrame, mean: float = 2.0) -> DataFrame:
    """p from the exponential distribution function of the weight."""
    return edges.withColumn("p", 1 - F.exp(-F.col("w") / F.lit(float(mean))))


def uniform(edges: DataFrame, salt: int = 11, kind: str = "md5") -> DataFrame:
    """p uniform per edge, a function of edge_id."""
    return edges.withColumn("p", coin(salt, F.col("edge_id"), kind=kind))


def given(edges: DataFrame, column: str | float) -> DataFrame:
    """p from a column or a constant; null or out-of-range values raise an error when read."""
    p = F.col(column).cast("double") if isinstance(column, str) else F.lit(float(column))
    return edges.withColumn("p", F.when(p.between(0, 1), p).otherwise(F.raise_error(F.lit("a probability is null or outside [0, 1]")).cast("double")))


def prepare(edges: DataFrame, mean: float = 2.0) -> DataFrame:
    """edges(edge_id, src, dst, w, p), written once."""
    return materialize(exponential(with_edge_ids(edges), mean).select("edge_id", "src", "dst", "w", "p"), "edges")


def random_seeds(edges: DataFrame, k: int, salt: int = 5) -> DataFrame:
    """k source nodes with the least hash."""
    nodes = edges.select(F.col("src").alias("seed")).distinct()
    return nodes.withColumn("h", coin(salt, F.col("seed"))).orderBy("h", "seed").limit(k).select("seed")
