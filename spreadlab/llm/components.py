"""Connected components by alternating star steps, for edge tables of any size and hubs of any degree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadlab.storage import discard, materialize, scratch_scope


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One step: neighbours (larger ones only, or smaller ones only) are hooked to the least neighbour.

    The least neighbours are written first, so the join below is between two plain shuffles and
    adaptive execution may split a hub's rows.
    """
    if large:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        both = edges
    least = materialize(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")).withColumnRenamed("u", "w"), "cc-least")
    met = both.join(least, F.col("u") == F.col("w"))
    if large:
        return met.filter("v > u AND v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    hooked = met.filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return hooked.unionByName(least.filter("w <> m").select(F.col("w").alias("u"), F.col("m").alias("v")))


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", most_rounds: int = 60) -> DataFrame:
    """(node, component) of every node that has an edge to another; component is its least node."""
    pairs = edges.select(F.greatest(a, b).cast("long").alias("u"), F.least(a, b).cast("long").alias("v")).filter("u <> v").distinct()
    pairs = materialize(pairs, "cc-edges")
    mark = None
    for _ in range(most_rounds):
        before = pairs
        with scratch_scope(edges.sparkSession) as made:
            pairs = materialize(_star(_star_written(before, True), False).distinct(), "cc-edges")
            made.remove(pairs._scratch)
        discard(before)
        now = tuple(pairs.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).collect()[0])
        if now == mark or not now[0]:
            break
        mark = now
    else:
        raise RuntimeError("components did not settle")
    roots = pairs.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return pairs.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)


def _star_written(pairs: DataFrame, large: bool) -> DataFrame:
    return materialize(_star(pairs, large).distinct(), "cc-star")
