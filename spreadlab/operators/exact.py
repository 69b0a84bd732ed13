"""Exact influence by enumeration of worlds, for micro graphs; a world is the bits of one number."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

MOST_EDGES = 20


def micro(edges: DataFrame) -> list[tuple[int, int, int, float]]:
    """(edge_id, src, dst, p) of a graph of at most MOST_EDGES edges, in edge_id order."""
    rows = edges.select("edge_id", "src", "dst", "p").orderBy("edge_id").limit(MOST_EDGES + 1).collect()
    if len(rows) > MOST_EDGES:
        raise ValueError(f"enumeration takes at most {MOST_EDGES} edges")
    return [tuple(r) for r in rows]


def _bit(x: Column, i: Column | int) -> Column:
    return F.call_function("shiftright", x, i if isinstance(i, Column) else F.lit(i)).bitwiseAND(1)


def world_probability(p: list[float], world: Column, first: int = 0) -> Column:
    """Product over the edges of p where the world's bit is set and 1 - p elsewhere."""
    return reduce(lambda acc, i: acc * F.when(_bit(world, i + first) == 1, F.lit(float(p[i]))).otherwise(F.lit(1 - float(p[i]))), range(len(p)), F.lit(1.0))


def spread(edges: list[tuple[int, int, int, float]], seed: int, world: Column) -> Column:
    """Nodes that the seed reaches in a world, the seed not counted; the reached set is a bit mask.

    Each node's live successors are one mask; the reached set grows by its members' masks, once per node.
    """
    nodes = sorted({seed, *(n for _, a, b, _ in edges for n in (a, b))})
    at = {n: i for i, n in enumerate(nodes)}
    if not edges:
        return F.lit(0).cast("long")
    none = F.lit(0).cast("long")
    after = F.array(*(reduce(Column.bitwiseOR, (F.call_function("shiftleft", _bit(world, i), F.lit(at[b])) for i, (_, a, b, _) in enumerate(edges) if a == n), none) for n in nodes))
    grow = lambda mask, masks: reduce(Column.bitwiseOR, (F.when(_bit(mask, v) == 1, F.get(masks, F.lit(v))).otherwise(none) for v in range(len(nodes))), mask)
    mask = F.aggregate(F.array_repeat(after, len(nodes) - 1), F.lit(1 << at[seed]).cast("long"), grow)
    return (F.bit_count(mask) - 1).cast("long")


def worlds(spark: SparkSession, edges: DataFrame, seed: int, fixed: dict[int, int] | None = None) -> DataFrame:
    """(world, pr, f) of every world that agrees with the fixed statuses {edge_id: 0 or 1}; pr is conditional on them."""
    rows = micro(edges)
    known = {i: (fixed or {})[e[0]] for i, e in enumerate(rows) if e[0] in (fixed or {})}
    free = [i for i in range(len(rows)) if i not in known]
    # spread the bits of a dense number over the free edges
    dense, world = F.col("id"), F.lit(sum(s << i for i, s in known.items())).cast("long")
    for j, i in enumerate(free):
        world = world.bitwiseOR(F.call_function("shiftleft", _bit(dense, j), F.lit(i)))
    base = spark.range(1 << len(free)).select("id", world.alias("world"))
    return base.select("world", world_probability([rows[i][3] for i in free], F.col("id")).alias("pr"), spread(rows, seed, F.col("world")).alias("f"))


def by_bits(spark: SparkSession, edges: DataFrame, seed: int, fixed: dict[int, int] | None = None) -> DataFrame:
    """(spread, variance, total_probability): the definition, one aggregate over all worlds."""
    w = worlds(spark, edges, seed, fixed).agg(F.sum(F.col("pr") * F.col("f")).alias("spread"), F.sum(F.col("pr") * F.col("f") * F.col("f")).alias("square"), F.sum("pr").alias("total_probability"))
    return w.select("spread", (F.col("square") - F.col("spread") * F.col("spread")).alias("variance"), "total_probability")


def divide(spark: SparkSession, edges: DataFrame, seed: int, r: int) -> DataFrame:
    """(spread): divide and conquer, r edges a level; children multiply the parent's mass, the last level takes what is left."""
    rows, level, done = micro(edges), spark.range(1).select(F.lit(0).cast("long").alias("world"), F.lit(1.0).alias("pi")), 0
    while done < len(rows):
        take = min(r, len(rows) - done)
        child = F.explode(F.sequence(F.lit(0).cast("long"), F.lit((1 << take) - 1).cast("long")))
        level = level.withColumn("child", child).select(F.col("world").bitwiseOR(F.call_function("shiftleft", F.col("child"), F.lit(done))).alias("world"), (F.col("pi") * world_probability([e[3] for e in rows[done : done + take]], F.col("child"))).alias("pi"))
        done += take
    return level.agg(F.sum(F.col("pi") * spread(rows, seed, F.col("world"))).alias("spread"))


def stratum_of(scheme: str, picked: list[int], world: Column) -> Column:
    """Number of the stratum (cube or staircase over the picked edge positions) that a world lies in."""
    if scheme == "cube":
        return sum((F.call_function("shiftleft", _bit(world, i), F.lit(j)) for j, i in enumerate(picked)), F.lit(0).cast("long"))
    out = F.lit(0)
    for j, i in reversed(list(enumerate(picked))):
        out = F.when(_bit(world, i) == 1, j + 1).otherwise(out)
    return out.cast("long")


def variance_parts(spark: SparkSession, edges: DataFrame, seed: int, scheme: str, picked: list[int], n: int) -> DataFrame:
    """(naive, basic, gap): exact variances of the naive and the proportionally stratified mean, and the variance between strata over n."""
    w = worlds(spark, edges, seed).withColumn("stratum", stratum_of(scheme, picked, F.col("world")))
    s = w.groupBy("stratum").agg(F.sum("pr").alias("pi"), (F.sum(F.col("pr") * F.col("f")) / F.sum("pr")).alias("mu"), (F.sum(F.col("pr") * F.col("f") * F.col("f")) / F.sum("pr")).alias("sq")).filter("pi > 0")
    t = s.agg(F.sum(F.col("pi") * F.col("mu")).alias("m"), F.sum(F.col("pi") * F.col("sq")).alias("q"), F.sum(F.col("pi") * (F.col("sq") - F.col("mu") * F.col("mu"))).alias("inside"), F.sum(F.col("pi") * F.col("mu") * F.col("mu")).alias("mm"))
    return t.select(((F.col("q") - F.col("m") * F.col("m")) / n).alias("naive"), (F.col("inside") / n).alias("basic"), ((F.col("mm") - F.col("m") * F.col("m")) / n).alias("gap"))
