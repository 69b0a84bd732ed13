"""Sample sizes of strata: proportional with rounding, variance-aware, or one grid slot per draw."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spreadlab.functions.coins import coin


def nearest(strata: DataFrame, n: int, least: int) -> DataFrame:
    """strata(.., pi) + n: pi * n rounded half up, at least ``least`` (1: never dropped, 0: may be dropped)."""
    return strata.withColumn("n", F.greatest(F.lit(least), F.floor(F.col("pi") * n + 0.5)).cast("long"))


def optimal(strata: DataFrame, n: int) -> DataFrame:
    """strata(.., pi, variance) + n: proportional to pi times the root of the variance, as real numbers (a bound, not a plan)."""
    share = F.col("pi") * F.sqrt("variance")
    total = F.sum(share).over(Window.partitionBy(F.lit(1)))
    return strata.withColumn("n", F.when(total > 0, n * share / F.nullif(total, F.lit(0.0))))


def grid(strata: DataFrame, n: int, reps: int, salt: int, path: str = "") -> DataFrame:
    """(rep, child, n) of strata(child, lo, hi): each of n draws has slot (k + u_k) / n and falls into one interval."""
    k = strata.sparkSession.range(reps * n).select(F.floor(F.col("id") / n).cast("int").alias("rep"), (F.col("id") % n).alias("k"))
    slots = k.withColumn("slot", (F.col("k") + coin(salt, F.col("rep"), F.lit(path), F.col("k"))) / n)
    met = slots.join(F.broadcast(strata.select("child", "lo", "hi")), (F.col("slot") >= F.col("lo")) & (F.col("slot") < F.col("hi")))
    return met.groupBy("rep", "child").agg(F.count(F.lit(1)).alias("n"))
