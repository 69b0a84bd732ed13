"""Reach of seeds in worlds drawn by coins: relational frontier, bit-packed words, in-memory words.

A world is never written down: an edge's coin is a function of (salt, rep, draw, edge_id), so it is
thrown only when the edge's source is reached, and throws alike in every engine.
draws(seed, rep, draw); fixed(seed, rep, draw, edge_id, status) overrides coins.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadlab.functions.coins import coin
from spreadlab.storage import discard, materialize

KEYS = ("seed", "rep", "draw")
MOST_PARTS = 16


def _together(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _compacted(parts: list[DataFrame], label: str) -> list[DataFrame]:
    """Hops are appended as parts of their own; many small parts are written as one now and then."""
    if len(parts) < MOST_PARTS:
        return parts
    whole = materialize(_together(parts), label)
    discard(*parts)
    return [whole]


def closure(edges: DataFrame, seeds: DataFrame) -> DataFrame:
    """Edges that some seed can reach if all edges exist; the rest never matters."""
    front = materialize(seeds.select(F.col("seed").alias("node")).distinct(), "closure")
    parts = [front]
    while not front.isEmpty():
        new = edges.join(front, F.col("src") == F.col("node"), "left_semi").select(F.col("dst").alias("node")).distinct().join(_together(parts), "node", "left_anti")
        front = materialize(new, "closure")
        parts = [*_compacted(parts, "closure"), front]
    return edges.join(_together(parts), F.col("src") == F.col("node"), "left_semi")


def frontier(edges: DataFrame, draws: DataFrame, salt: int = 7, kind: str = "md5", fixed: DataFrame | None = None, hops: int | None = None) -> DataFrame:
    """(seed, rep, draw, node, hop) of every reached node, the seed at hop 0.

    Each hop joins the newly reached nodes with their out-edges, throws the coins, and drops nodes
    that were reached before. Every hop is written as a part of its own, so lineage stays short and
    nothing is written twice but for rare compaction.
    """
    front = materialize(draws.select(*KEYS, F.col("seed").alias("node"), F.lit(0).alias("hop")), "reach")
    parts, hop = [front], 0
    while hops is None or hop < hops:
        hop += 1
        tried = front.join(edges.select("edge_id", "src", "dst", "p"), F.col("node") == F.col("src"))
        live = coin(salt, F.col("rep"), F.col("draw"), F.col("edge_id"), kind=kind) < F.col("p")
        if fixed is not None:
            tried = tried.join(fixed.select(*KEYS, "edge_id", "status"), [*KEYS, "edge_id"], "left")
            live = F.when(F.col("status").isNotNull(), F.col("status") == 1).otherwise(live)
        new = tried.filter(live).select(*KEYS, F.col("dst").alias("node")).distinct().join(_together(parts).select(*KEYS, "node"), [*KEYS, "node"], "left_anti")
        front = materialize(new.withColumn("hop", F.lit(hop)), "reach")
        if front.isEmpty():
            break
        parts = [*_compacted(parts, "reach"), front]
    return _together(parts)


def packed(edges: DataFrame, seeds: DataFrame, n: int, reps: int = 1, salt: int = 7, kind: str = "md5", fixed: DataFrame | None = None) -> DataFrame:
    """(seed, rep, node, word, bits): 64 draws to a row; bit b of word w is draw 64 w + b.

    fixed(seed, rep, draw, edge_id, status) is packed the same way: bits that are on, bits that are off.
    """
    words = -(-n // 64)
    draw = lambda b: F.col("word") * 64 + b
    state = seeds.select("seed").withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1)))).withColumn("word", F.explode(F.sequence(F.lit(0), F.lit(words - 1))))
    full = F.when(F.col("word") * 64 + 64 <= n, F.lit(-1).cast("long")).otherwise(F.lit((1 << (n % 64)) - 1 if n % 64 else -1).cast("long"))
    front = materialize(state.select("seed", "rep", F.col("seed").alias("node"), "word", full.alias("bits")), "packed")
    keys, parts = ["seed", "rep", "node", "word"], [front]
    bits = F.aggregate(
        F.sequence(F.lit(0), F.lit(63)),
        F.lit(0).cast("long"),
        lambda acc, b: F.when(coin(salt, F.col("rep"), draw(b), F.col("edge_id"), kind=kind) < F.col("p"), acc.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), b))).otherwise(acc),
    )
    if fixed is not None:
        one = F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("draw") % 64).cast("int"))
        none = F.lit(0).cast("long")
        known = fixed.withColumn("word", F.floor(F.col("draw") / 64).cast("int")).groupBy("seed", "rep", "word", "edge_id")
        known = materialize(known.agg(F.bit_or(F.when(F.col("status") == 1, one).otherwise(none)).alias("on"), F.bit_or(F.when(F.col("status") == 0, one).otherwise(none)).alias("off")), "packed-fixed")
        bits = bits.bitwiseAND(F.bitwise_not(F.coalesce("off", none))).bitwiseOR(F.coalesce("on", none))
    while True:
        tried = front.join(edges.select("edge_id", "src", "dst", "p"), F.col("node") == F.col("src"))
        if fixed is not None:
            tried = tried.withColumnRenamed("bits", "came").join(known, ["seed", "rep", "word", "edge_id"], "left").withColumnRenamed("came", "bits")
        hit = tried.withColumn("go", F.col("bits").bitwiseAND(bits)).filter("go <> 0").groupBy("seed", "rep", F.col("dst").alias("node"), "word").agg(F.bit_or("go").alias("go"))
        seen = _together(parts).groupBy(*keys).agg(F.bit_or("bits").alias("bits"))
        new = hit.join(seen, keys, "left").withColumn("fresh", F.col("go").bitwiseAND(F.bitwise_not(F.coalesce("bits", F.lit(0).cast("long"))))).filter("fresh <> 0")
        front = materialize(new.select("seed", "rep", "node", "word", F.col("fresh").alias("bits")), "packed")
        if front.isEmpty():
            return seen
        parts = [*_compacted(parts, "packed"), front]


def spread_of(reached: DataFrame) -> DataFrame:
    """(seed, rep, draw, f): nodes reached, the seed not counted."""
    return reached.groupBy(*KEYS).agg((F.count(F.lit(1)) - 1).alias("f"))


def spread_of_packed(bits: DataFrame, n: int) -> DataFrame:
    """As spread_of: 64 sums a word, opened only after they are added up."""
    sums = F.array(*(F.sum(F.call_function("shiftright", F.col("bits"), F.lit(b)).bitwiseAND(1)) for b in range(64)))
    opened = bits.groupBy("seed", "rep", "word").agg(sums.alias("f")).select("seed", "rep", "word", F.posexplode("f").alias("bit", "f"))
    return opened.select("seed", "rep", (F.col("word") * 64 + F.col("bit")).cast("long").alias("draw"), (F.col("f") - 1).alias("f")).filter(F.col("draw") < n)


def outcome_of(reached: DataFrame, statistic: tuple) -> DataFrame:
    """(seed, rep, draw, f) of any target function of the reached nodes and their hops.

    ("spread",), ("reaches", t), ("reaches_within", t, hops), ("distance", t, value where t is not reached),
    ("connects", (t, ..)).
    """
    kind, *args = statistic
    if kind == "spread":
        return spread_of(reached)
    at = F.col("node") == F.lit(args[0]) if kind != "connects" else None
    value = {
        "reaches": lambda: F.max(F.when(at, 1.0).otherwise(0.0)),
        "reaches_within": lambda: F.max(F.when(at & (F.col("hop") <= args[1]), 1.0).otherwise(0.0)),
        "distance": lambda: F.coalesce(F.min(F.when(at, F.col("hop"))).cast("double"), F.lit(float(args[1]))),
        "connects": lambda: (F.count_distinct(F.when(F.col("node").isin(list(args[0])), F.col("node"))) == len(set(args[0]))).cast("double"),
    }
    if kind not in value:
        raise ValueError(f"unknown target {kind}")
    return reached.groupBy(*KEYS).agg(value[kind]().alias("f"))


def coins_thrown(edges: DataFrame, reached: DataFrame, fixed: DataFrame | None = None) -> DataFrame:
    """(seed, rep, coins): one coin per out-edge of each reached (draw, node), but for fixed statuses."""
    degree = edges.groupBy(F.col("src").alias("node")).agg(F.count(F.lit(1)).alias("out"))
    thrown = reached.join(degree, "node").groupBy("seed", "rep").agg(F.sum("out").alias("coins"))
    if fixed is None:
        return thrown
    known = fixed.join(edges.select("edge_id", F.col("src").alias("node")), "edge_id").join(reached.select(*KEYS, "node"), [*KEYS, "node"], "left_semi")
    spared = known.groupBy("seed", "rep").agg(F.count(F.lit(1)).alias("spared"))
    return thrown.join(spared, ["seed", "rep"], "left").select("seed", "rep", (F.col("coins") - F.coalesce("spared", F.lit(0))).alias("coins"))
