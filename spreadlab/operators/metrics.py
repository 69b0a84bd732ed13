"""Accuracy measures over estimates(estimator, seed, rep, f_hat, ..)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def replicate_variance(estimates: DataFrame) -> DataFrame:
    """(estimator, seed, mean, variance, reps): sample variance over runs, divisor reps - 1."""
    return estimates.groupBy("estimator", "seed").agg(F.avg("f_hat").alias("mean"), F.var_samp("f_hat").alias("variance"), F.count(F.lit(1)).alias("reps"))


def relative_variance(estimates: DataFrame, base: str = "naive") -> DataFrame:
    """(estimator, mean_of_ratios, ratio_of_means, seeds, excluded): variance over the base's, by seed.

    A seed whose base variance is 0 has no ratio; it is left out and counted.
    """
    v = replicate_variance(estimates)
    b = v.filter(F.col("estimator") == base).select("seed", F.col("variance").alias("base"))
    met = v.join(b, "seed").withColumn("ratio", F.when(F.col("base") > 0, F.col("variance") / F.col("base")))
    return met.groupBy("estimator").agg(F.avg("ratio").alias("mean_of_ratios"), (F.sum("variance") / F.sum("base")).alias("ratio_of_means"), F.count("ratio").alias("seeds"), F.count(F.when(F.col("ratio").isNull(), 1)).alias("excluded"))


def mse(estimates: DataFrame, exact: DataFrame) -> DataFrame:
    """(estimator, seed, mse, bias, variance, z): against exact(seed, spread); mse = variance (divisor reps) + bias squared."""
    met = estimates.join(exact, "seed").withColumn("error", F.col("f_hat") - F.col("spread"))
    out = met.groupBy("estimator", "seed").agg(F.avg(F.col("error") * F.col("error")).alias("mse"), F.avg("error").alias("bias"), F.var_pop("f_hat").alias("variance"), (F.stddev_samp("f_hat") / F.sqrt(F.count(F.lit(1)))).alias("se"))
    return out.withColumn("z", F.when(F.col("se") > 0, F.col("bias") / F.col("se"))).drop("se")


def reduction_pct(relative: DataFrame, base: str) -> DataFrame:
    """(estimator, reduction): (base - estimator) / estimator in per cent."""
    b = relative.filter(F.col("estimator") == base).select(F.col("mean_of_ratios").alias("b"))
    return relative.join(F.broadcast(b.limit(1)), F.lit(True)).select("estimator", (100 * (F.col("b") / F.col("mean_of_ratios") - 1)).alias("reduction"))


def worst_case_variance(n_draws: int, n_nodes: int) -> float:
    """Sample variance when half the draws reach nothing and half reach all."""
    return n_draws * (n_nodes - 1) ** 2 / (4 * (n_draws - 1))


def counters(estimates: DataFrame) -> DataFrame:
    """(estimator, draws, coins, tree_nodes, mean_depth): work per run, averaged."""
    return estimates.groupBy("estimator").agg(*(F.avg(c).alias(c) for c in ("draws", "coins", "tree_nodes", "mean_depth")))
