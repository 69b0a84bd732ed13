"""SQL surface: a table function for strata, and estimates over a registered view."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadlab.operators.local import masses, statuses
from spreadlab.plans.estimators import SampleSpec, estimate


class Strata:
    """strata(probabilities array<double>, scheme) -> one row per stratum with mass."""

    def eval(self, probabilities: list, scheme: str) -> Iterator[tuple]:
        pi, consumed = masses(np.array(probabilities, float), scheme)
        for child, (mass, used) in enumerate(zip(pi.tolist(), consumed.tolist(), strict=True)):
            if mass > 0:
                yield child, mass, used, statuses(scheme, child, len(probabilities)).tolist()


def register(spark: SparkSession) -> None:
    """Make ``SELECT * FROM strata(array(0.6D, 0.3D), 'cube')`` available in this session."""
    spark.udtf.register("strata", F.udtf(Strata, returnType="child int, pi double, consumed int, status array<int>"))


def influence(spark: SparkSession, view: str, seed: int, method: str = "cube_recursive_bfs", n: int = 1000, **options) -> DataFrame:
    """Estimate the spread of one node on a view of edges(edge_id, src, dst, p)."""
    return estimate(spark.table(view), spark.createDataFrame([(seed,)], "seed long"), method, spec=SampleSpec(n=n), **options)
