"""Cube and staircase strata of the next r edges at a cursor."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

MOST_CUBE_EDGES = 16


def selected(order: DataFrame, cursors: DataFrame, r: int, keys: tuple[str, ...]) -> DataFrame:
    """(keys, cursor, ps, ids): the r edges from each cursor on, in order; shorter rests are left out."""
    met = cursors.join(order, list(keys)) if keys else cursors.join(order, F.lit(True))
    met = met.filter((F.col("ord") >= F.col("cursor")) & (F.col("ord") < F.col("cursor") + r))
    got = met.groupBy(*keys, "cursor").agg(F.sort_array(F.collect_list(F.struct("ord", "p", "edge_id"))).alias("s"))
    return got.filter(F.size("s") == r).select(*keys, "cursor", F.col("s.p").alias("ps"), F.col("s.edge_id").alias("ids"))


def _mass(r: int, status: Column, upto: Column) -> Column:
    """Product over the first ``upto`` edges of p or 1 - p by status."""
    return F.aggregate(F.sequence(F.lit(0), F.lit(r - 1)), F.lit(1.0), lambda acc, j: F.when(j >= upto, acc).when(F.get(status, j) == 1, acc * F.get("ps", j)).otherwise(acc * (1 - F.get("ps", j))))


def strata(picked: DataFrame, scheme: str, r: int, keys: tuple[str, ...]) -> DataFrame:
    """(keys, cursor, child, pi, lo, hi, consumed, status, ids) of every stratum with mass.

    cube: child's bit j is edge j's status (edge 0 toggles fastest), r edges consumed.
    staircase: child 0 has all r absent; child i has i - 1 absent, then one present, i consumed.
    """
    if scheme == "cube":
        if r > MOST_CUBE_EDGES:
            raise ValueError(f"a cube of {r} edges has too many strata")
        rows = picked.withColumn("child", F.explode(F.sequence(F.lit(0), F.lit((1 << r) - 1))))
        rows = rows.withColumn("consumed", F.lit(r)).withColumn("status", F.transform(F.sequence(F.lit(0), F.lit(r - 1)), lambda j: F.call_function("shiftright", F.col("child"), j).bitwiseAND(1)))
    elif scheme == "staircase":
        rows = picked.withColumn("child", F.explode(F.sequence(F.lit(0), F.lit(r))))
        rows = rows.withColumn("consumed", F.when(F.col("child") == 0, r).otherwise(F.col("child"))).withColumn("status", F.transform(F.sequence(F.lit(1), F.col("consumed")), lambda j: (j == F.col("child")).cast("int")))
    else:
        raise ValueError(f"unknown scheme {scheme}")
    rows = rows.withColumn("pi", _mass(r, F.col("status"), F.col("consumed"))).filter("pi > 0")
    total = F.sum("pi").over(Window.partitionBy(*keys, "cursor").orderBy("child").rowsBetween(Window.unboundedPreceding, 0))
    rows = rows.withColumn("hi", total).withColumn("lo", F.col("hi") - F.col("pi"))
    last = F.row_number().over(Window.partitionBy(*keys, "cursor").orderBy(F.desc("child"))) == 1
    rows = rows.withColumn("hi", F.when(last, 2.0).otherwise(F.col("hi")))  # rounding must not leave a gap at 1
    edge = F.lag("hi", 1, 0.0).over(Window.partitionBy(*keys, "cursor").orderBy("child"))
    return rows.withColumn("lo", edge).select(*keys, "cursor", "child", "pi", "lo", "hi", "consumed", "status", "ids")
