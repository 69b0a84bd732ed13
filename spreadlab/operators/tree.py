"""Level-synchronous stratum tree: all open tree nodes of a depth split in one plan."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadlab.functions.coins import coin
from spreadlab.operators.strata import selected, strata
from spreadlab.storage import materialize

KEYS = ("seed", "rep")


@dataclass
class Plan:
    """draws(seed, rep, draw, path, cursor, k, n), fixed(seed, rep, draw, edge_id, status), levels split."""

    draws: DataFrame
    fixed: DataFrame | None
    depth: int


def root_draws(spark: SparkSession, seeds: DataFrame, reps: int, n: int) -> DataFrame:
    """The draws of every run, at the root."""
    numbered = spark.range(reps * n).select(F.floor(F.col("id") / n).cast("int").alias("rep"), (F.col("id") % n).alias("draw"))
    return seeds.select("seed").join(numbered, F.lit(True)).select("seed", "rep", "draw", F.lit("").alias("path"), F.lit(0).cast("long").alias("cursor"), F.col("draw").alias("k"), F.lit(n).cast("long").alias("n"))


def grow(order: Callable[[int], DataFrame], draws: DataFrame, scheme: str, r: int, tau: int = 10, depth: int | None = None, salt: int = 7, kind: str = "md5") -> Plan:
    """Split open nodes until each has fewer than ``tau`` draws or fewer than r edges left (or ``depth`` levels).

    ``order(limit)`` gives the first ``limit`` edges of each run's order, or fewer where there are no more;
    a longer prefix is asked for when a node's cursor comes near its end. A node's n draws take one grid
    slot each, (k + u_k) / n with hashed u_k, and go to the stratum whose interval holds it: sizes sum
    exactly, and the plain mean over all draws stays unbiased.
    """
    done, fixed, open_, level, limit, keys, lengths, prefix = [], [], draws, 0, 0, (), None, None
    furthest = 0
    while depth is None or level < depth:
        if furthest + r > limit:
            limit = max(4 * limit, 8 * r, 64, furthest + r)
            prefix = materialize(order(limit), "tree-order")
            keys = tuple(k for k in KEYS if k in prefix.columns)
            lengths = materialize(prefix.groupBy(*keys).agg((F.max("ord") + 1).alias("edges")), "tree-lengths")
            prefix = prefix.select(*keys, "ord", "edge_id", "p")
        sized = open_.join(lengths, list(keys), "left")
        leaf = (F.coalesce("edges", F.lit(0)) - F.col("cursor") < r) | ((F.col("n") < tau) if depth is None else F.lit(False))
        done.append(sized.filter(leaf).drop("edges"))
        open_ = sized.filter(~leaf).drop("edges")
        picked = selected(prefix, open_.select(*keys, "cursor").distinct(), r, keys)
        parts = strata(picked, scheme, r, keys).withColumnRenamed("cursor", "at")
        slot = (F.col("k") + coin(salt, F.col("rep"), F.col("path"), F.col("k"), kind=kind)) / F.col("n")
        met = open_.withColumn("slot", slot).join(parts.withColumnsRenamed({k: f"s_{k}" for k in keys}), [F.col(k) == F.col(f"s_{k}") for k in keys] + [F.col("cursor") == F.col("at"), F.col("slot") >= F.col("lo"), F.col("slot") < F.col("hi")])
        met = met.withColumn("path", F.concat("path", F.lit("."), F.col("child").cast("string")))
        node = Window.partitionBy("seed", "rep", "path")
        met = met.withColumn("k", F.row_number().over(node.orderBy("draw")) - 1).withColumn("n", F.count(F.lit(1)).over(node))
        met = materialize(met.select("seed", "rep", "draw", "path", (F.col("cursor") + F.col("consumed")).alias("cursor"), F.col("k").cast("long").alias("k"), "n", F.slice("ids", F.lit(1), F.col("consumed")).alias("ids"), "status"), "tree-level")
        open_ = None
        furthest = met.agg(F.max("cursor")).collect()[0][0]
        if furthest is None:
            break
        fixed.append(met.select("seed", "rep", "draw", F.explode(F.arrays_zip("ids", "status")).alias("x")).select("seed", "rep", "draw", F.col("x.ids").alias("edge_id"), F.col("x.status").cast("int").alias("status")))
        open_, level = met.drop("ids", "status"), level + 1
    done += [open_] if open_ is not None else []
    return Plan(reduce(DataFrame.unionByName, done), reduce(DataFrame.unionByName, fixed) if fixed else None, level)


def tree_size(draws: DataFrame) -> DataFrame:
    """(seed, rep, tree_nodes, mean_depth) of draws at their leaves: every prefix of a path is a node."""
    depth = F.size(F.split("path", r"\.")) - 1
    leaves = draws.groupBy("seed", "rep", "path").agg(F.count(F.lit(1)).alias("size")).withColumn("depth", depth)
    nodes = leaves.select("seed", "rep", F.explode(F.transform(F.sequence(F.lit(0), "depth"), lambda i: F.call_function("substring_index", "path", F.lit("."), i + 1))).alias("node")).groupBy("seed", "rep").agg(F.count_distinct("node").alias("tree_nodes"))
    mean = leaves.groupBy("seed", "rep").agg((F.sum(F.col("size") * F.col("depth")) / F.sum("size")).alias("mean_depth"))
    return nodes.join(mean, ["seed", "rep"])
