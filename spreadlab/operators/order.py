"""Edge orders from which stratified estimators take their edges: breadth-first, or one hashed permutation per run."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spreadlab.functions.coins import MD5_BLOCK, coin, coin_below, md5_coins
from spreadlab.storage import materialize


def bfs_edges(edges: DataFrame, seeds: DataFrame, limit: int | None = None) -> DataFrame:
    """(seed, ord, edge_id, src, dst, p): out-edges of nodes in discovery order, by dst within a node.

    Edges to nodes that are known already are included. With a limit only the first ``limit`` edges of a
    seed are followed in any hop, so neither a long graph nor a hub is walked for a short prefix.
    """
    front = materialize(seeds.select("seed", F.col("seed").alias("node"), F.lit(0).cast("long").alias("nord")), "bfs-nodes")
    seen, found, base = [front], [], 1
    while True:
        out = front.join(edges.select("edge_id", "src", "dst", "p"), F.col("node") == F.col("src")).select("seed", "nord", "edge_id", "src", "dst", "p")
        if limit is not None:
            out = out.withColumn("nth", F.row_number().over(Window.partitionBy("seed").orderBy("nord", "dst"))).filter(F.col("nth") <= limit).drop("nth")
        out = materialize(out, "bfs-edges")
        found.append(out)
        known = reduce(DataFrame.unionByName, seen).select("seed", "node")
        new = out.groupBy("seed", F.col("dst").alias("node")).agg(F.min(F.struct("nord", "dst")).alias("first")).join(known, ["seed", "node"], "left_anti")
        front = materialize(new.select("seed", "node", (F.row_number().over(Window.partitionBy("seed").orderBy("first")) + base - 1).cast("long").alias("nord")), "bfs-nodes")
        if front.isEmpty():
            break
        base = front.agg(F.max("nord")).collect()[0][0] + 1
        seen.append(front)
        if limit is not None and reduce(DataFrame.unionByName, found).groupBy("seed").count().agg(F.min("count")).collect()[0][0] >= limit:
            break
    ranked = reduce(DataFrame.unionByName, found).withColumn("ord", (F.row_number().over(Window.partitionBy("seed").orderBy("nord", "dst")) - 1).cast("long"))
    ranked = ranked if limit is None else ranked.filter(F.col("ord") < limit)
    return ranked.select("seed", "ord", "edge_id", "src", "dst", "p")


def low_coins(edges: DataFrame, reps: int, salt: int, share: float) -> DataFrame:
    """(edge_id, src, dst, p, rep, u) of the edges whose md5 coin u of a run's order is below ``share``; many are hashed at a time."""

    def below(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for b in batches:
            held.append(b)
            size += b.num_rows
            if size >= MD5_BLOCK:
                yield from thrown(held)
                held, size = [], 0
        if held:
            yield from thrown(held)

    def thrown(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(held)
        ids = rows["edge_id"].to_numpy()
        for rep in range(reps):
            u = md5_coins(f"{salt}|order|{rep}", ids)
            some = np.flatnonzero(u < share)
            if len(some):
                part = rows.take(some).append_column("rep", pa.array(np.full(len(some), rep, np.int32))).append_column("u", pa.array(u[some]))
                yield from part.combine_chunks().to_batches()

    columns = [F.col(c).cast("long").alias(c) for c in ("edge_id", "src", "dst")]
    return edges.filter("edge_id IS NOT NULL").select(*columns, F.col("p").cast("double").alias("p")).mapInArrow(below, "edge_id long, src long, dst long, p double, rep int, u double")


def random_edges(edges: DataFrame, reps: int, salt: int = 7, kind: str = "md5", limit: int | None = None) -> DataFrame:
    """(rep, ord, edge_id, src, dst, p): a hashed permutation of all edges per run.

    With a limit only edges of a hash below a threshold are sorted, a little more than ``limit`` of a run;
    the threshold rises until every run has enough.
    """
    each = edges.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))
    keys = salt, "order", F.col("rep"), F.col("edge_id")
    rows = each.withColumn("u", coin(*keys, kind=kind))
    if limit is not None and (m := edges.count()) > limit:
        share = (limit + 6 * limit**0.5 + 20) / m
        while share < 1:
            low = materialize(low_coins(edges, reps, salt, share) if kind == "md5" else each.filter(coin_below(share, *keys, kind=kind)).withColumn("u", coin(*keys, kind=kind)), "order-prefix")
            counts = low.groupBy("rep").count().agg(F.min("count"), F.count(F.lit(1))).collect()[0]
            if counts[1] == reps and counts[0] >= limit:
                rows = low
                break
            share *= 2
    ranked = rows.withColumn("ord", (F.row_number().over(Window.partitionBy("rep").orderBy("u", "edge_id")) - 1).cast("long"))
    ranked = ranked if limit is None else ranked.filter(F.col("ord") < limit)
    return ranked.select("rep", "ord", "edge_id", "src", "dst", "p")
