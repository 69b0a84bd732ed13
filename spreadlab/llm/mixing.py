"""Mix sources to target weights with a multivariate-hypergeometric splitting tree.

Targets: sources share a total by weight, none above ``most_repeats`` times its size, the excess
reshared by weight. A source's target is a number of whole passes over all its documents plus a
remainder that is drawn without replacement. For the remainder the documents are cut into blocks,
dealt to output shards by a hash, and the remainder's exact quota of words is split down a binary
tree over the shards: at each node the left half gets a hypergeometric draw given the words that
lie there, so the shards' quotas are jointly multivariate hypergeometric and sum exactly. In its
shard a source's blocks are put in permuted order and taken until the quota is full; the last one
is cut. Blocks are disjoint, so a pass takes no word twice. All draws are functions of keys and a
seed: reruns and retried tasks agree. Each shard's passages are shuffled locally by a hash.

Only counts by source and shard (a number set by the shard count) reach one task; the blocks of a
source, however large, stay spread over the shards.

Defined cases: a null or empty text has size 0 and takes nothing; a null source is a source, last in
order; a null doc_id is mixed like any other; repeated rows are separate copies; an empty table or a
total of 0 gives rows with nothing taken.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadlab.llm.common import PIECE_ROWS, table, tidy
from spreadlab.storage import materialize

BLOCK_WORDS = 512
WEIGHTS = (5, 2, 1)
NUMPY_LIMIT = 900_000_000  # the library's sampler takes smaller populations only
WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def word_count(text: Column) -> Column:
    """Number of words; null has none. Counts the places where a word begins."""
    return F.coalesce(F.regexp_count(text, F.lit(r"(?<![^\x20\x09-\x0D])[^\x20\x09-\x0D]")), F.lit(0)).cast("long")


def share_out(sizes: pd.DataFrame, total_share: float, weights: tuple[float, ...], most_repeats: float) -> pd.DataFrame:
    """Targets of sources (source, source_size) in order: water-filling by weight under the caps."""
    keys = sorted(range(len(sizes)), key=lambda i: (sizes["source"][i] is None, sizes["source"][i] or ""))
    size = np.array([float(sizes["source_size"][i]) for i in keys])
    w = np.array([weights[i % len(weights)] for i in range(len(keys))], float)
    cap, left, open_ = most_repeats * size, total_share * size.sum(), np.ones(len(keys), bool)
    target = np.zeros(len(keys))
    while open_.any() and left > 0:
        share = np.where(open_, w * left / w[open_].sum(), 0.0)
        over = open_ & (share > cap)
        if not over.any():
            target[open_] = share[open_]
            break
        target[over] = cap[over]
        left -= cap[over].sum()
        open_ &= ~over
    return pd.DataFrame({"source": [sizes["source"][i] for i in keys], "source_size": [int(sizes["source_size"][i]) for i in keys], "target": target})


def hypergeometric(rng: np.random.Generator, left: int, right: int, draws: int) -> int:
    """Words out of ``draws`` that fall on the left side."""
    low, high = max(0, draws - right), min(draws, left)
    if low == high:
        return low
    if left + right < NUMPY_LIMIT:
        return int(rng.hypergeometric(left, right, draws))
    return ratio_of_uniforms(rng, left, right, draws)


def log_factorial_step(a: int, d: int) -> float:
    """log((a + d)! / a!) without the difference of two large logarithms."""
    if abs(d) <= 16 or min(a, a + d) < 1000:
        return math.lgamma(a + d + 1) - math.lgamma(a + 1) if max(a, a + d) < 1 << 20 else math.copysign(1, d) * sum(math.log(i) for i in range(min(a, a + d) + 1, max(a, a + d) + 1))
    z, y = a + 1.0, a + d + 1.0
    tail = (z - y) / (12 * y * z) - (1 / y**3 - 1 / z**3) / 360  # of the asymptotic series
    return (z - 0.5) * math.log1p(d / z) + d * (math.log(y) - 1) + tail


def ratio_of_uniforms(rng: np.random.Generator, left: int, right: int, draws: int) -> int:
    """Hypergeometric draw for populations of any size: rejection against the exact probability relative to the mode's."""
    n = left + right
    good, bad, m = min(left, right), max(left, right), min(draws, n - draws)
    mean = m * good / n
    mode = (m + 1) * (good + 1) // (n + 2)
    spread = math.sqrt(mean * (bad / n) * ((n - m) / (n - 1)) + 0.5)
    width = 2 * math.sqrt(2 / math.e) * spread + 3 - 2 * math.sqrt(3 / math.e)
    while True:
        u, v = 1.0 - rng.random(), rng.random()
        k = math.floor(mean + 0.5 + width * (v - 0.5) / u)
        if not max(0, m - bad) <= k <= min(m, good):
            continue
        d = k - mode
        if 2 * math.log(u) <= -(log_factorial_step(mode, d) + log_factorial_step(good - mode, -d) + log_factorial_step(m - mode, -d) + log_factorial_step(bad - m + mode, d)):
            break
    of_left = k if left <= right else m - k
    return of_left if m == draws else left - of_left


def split_quota(counts: np.ndarray, draws: int, seed: int) -> np.ndarray:
    """Exact quotas by shard: a hypergeometric split at every node of a binary tree over the shards."""
    before = np.concatenate([[0], np.cumsum(counts.astype(object))])
    out = np.zeros(len(counts), np.int64)
    nodes = [(0, len(counts), int(draws))]
    while nodes:
        a, b, k = nodes.pop()
        if k == 0:
            continue
        if b - a == 1:
            out[a] = k
            continue
        mid = (a + b) // 2
        left = hypergeometric(np.random.default_rng([seed, a, b]), int(before[mid] - before[a]), int(before[b] - before[mid]), k)
        nodes += [(a, mid, left), (mid, b, k - left)]
    return out


def targets_for(sized: DataFrame, total_share: float = 1.5, weights: tuple[float, ...] = WEIGHTS, most_repeats: float = 2.0) -> DataFrame:
    """(source, source_size, target, passes, rest) of each source in sized(source, size); source names are few by nature of a mix."""
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    whole = totals.groupBy(F.lit(0).alias("all")).applyInPandas(lambda p: share_out(p.reset_index(drop=True), total_share, weights, most_repeats), "source string, source_size long, target double")
    want = F.round("target").cast("long")
    return whole.withColumn("passes", F.when(F.col("source_size") > 0, F.floor(want / F.col("source_size"))).otherwise(0).cast("int")).withColumn("rest", F.when(F.col("source_size") > 0, want - F.col("passes") * F.col("source_size")).otherwise(0))


def shards_for(targets: DataFrame, block_words: int, blocks_each: int = 10_000) -> int:
    """Shards of a bounded number of blocks; it follows the data, not the session."""
    words = targets.agg(F.sum("source_size")).collect()[0][0] or 0
    return max(512, -(-words // (block_words * blocks_each)))


def draw_blocks(rows: DataFrame, targets: DataFrame, seed: int = 17, shards: int | None = None, block_words: int = BLOCK_WORDS) -> DataFrame:
    """(key, source, shard, first, words) of the blocks drawn for the remainder.

    rows(key, source, size): key identifies a row. A block is words [first, first + words) of its row.
    """
    shards = shards or shards_for(targets, block_words)
    here = F.struct("key", "first")
    some = targets.filter("rest > 0").select(F.col("source").alias("s"), "rest")
    blocks = rows.filter("size > 0").join(some, F.col("source").eqNullSafe(F.col("s"))).select("key", "source", "size", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("size") - 1) / block_words))).alias("nth"))
    blocks = blocks.select("key", "source", (F.col("nth") * block_words).alias("first"), F.least(F.lit(block_words).cast("long"), F.col("size") - F.col("nth") * block_words).alias("words"))
    blocks = blocks.withColumn("shard", F.pmod(F.xxhash64(here, F.lit(seed)), F.lit(shards)).cast("int"))
    counts = blocks.groupBy("source", "shard").agg(F.sum("words").alias("here")).join(some, F.col("source").eqNullSafe(F.col("s"))).drop("s")

    def quotas(p: pd.DataFrame) -> pd.DataFrame:
        p = p.sort_values("shard")
        name = p["source"].iloc[0]
        own = int.from_bytes(("" if name is None else "s" + name).encode()[:4096], "little") % (1 << 61) ^ seed
        dense = np.zeros(shards, np.int64)
        dense[p["shard"].to_numpy()] = p["here"].to_numpy()
        got = split_quota(dense, int(p["rest"].iloc[0]), own)
        return pd.DataFrame({"q_source": p["source"], "q_shard": p["shard"], "quota": got[p["shard"].to_numpy()]})

    quota = counts.groupBy("source").applyInPandas(quotas, "q_source string, q_shard int, quota long").filter("quota > 0")
    permuted = Window.partitionBy("source", "shard").orderBy(F.xxhash64(here, F.lit(seed + 1)), "key", "first").rowsBetween(Window.unboundedPreceding, 0)
    drawn = blocks.withColumn("until", F.sum("words").over(permuted)).join(quota, F.col("source").eqNullSafe(F.col("q_source")) & (F.col("shard") == F.col("q_shard")))
    drawn = drawn.withColumn("words", F.least("words", F.col("quota") - (F.col("until") - F.col("words")))).filter("words > 0")
    return drawn.select("key", "source", "shard", "first", "words")


def plan_mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = 17, total_share: float = 1.5, weights: tuple[float, ...] = WEIGHTS, most_repeats: float = 2.0) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(rows, targets, blocks): rows(key, source, size) narrow and written, so that keys stay the same."""
    rows = docs.select(row_key(id_col, text_col).alias("key"), F.col(source_col).cast("string").alias("source"), word_count(F.col(text_col)).alias("size"))
    same = Window.partitionBy("key.id", "key.hash").orderBy("source", "size")
    rows = materialize(rows.withColumn("copy", F.row_number().over(same)).select(F.struct("key.id", "key.hash", "copy").alias("key"), "source", "size"), "mix-rows")
    targets = materialize(targets_for(rows, total_share, weights, most_repeats), "mix-targets")
    return rows, targets, materialize(draw_blocks(rows, targets, seed), "mix-blocks")


def row_key(id_col: str, text_col: str):
    """Identity of a row: its id and its text's hash (a number tells repeated rows apart)."""
    return F.struct(F.col(id_col).cast("long").alias("id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("hash"))


def mix_counts(docs: DataFrame, **options) -> DataFrame:
    """(key, size, source_size, target, taken) of every row of ``docs``."""
    rows, targets, blocks = plan_mix(docs, **options)
    part = blocks.groupBy("key").agg(F.sum("words").alias("part")).withColumnRenamed("key", "k")
    named = targets.select(F.col("source").alias("s"), "source_size", "target", "passes")
    out = rows.join(named, F.col("source").eqNullSafe(F.col("s")), "left").join(part, F.col("key").eqNullSafe(F.col("k")), "left")
    return out.select("key", "size", "source_size", "target", (F.col("size") * F.col("passes") + F.coalesce("part", F.lit(0))).alias("taken"))


def mix_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **options) -> DataFrame:
    """The mix itself: rows of ``docs`` (same columns), whole passes as whole rows, the rest as passages.

    The join deals rows to tasks by a hash of their key; each task shuffles its rows by another hash.
    """
    rows, targets, blocks = plan_mix(docs, id_col, text_col, source_col, **options)
    pieces = blocks.groupBy(F.col("key").alias("k")).agg(F.sort_array(F.collect_list(F.struct("first", "words"))).alias("pieces"))
    passes = targets.select(F.col("source").alias("s"), "passes")
    plan = rows.join(passes, F.col("source").eqNullSafe(F.col("s"))).join(pieces, F.col("key").eqNullSafe(F.col("k")), "left").filter("passes > 0 OR pieces IS NOT NULL").select("key", "passes", "pieces")
    # the row travels as one column, so its names meet no others
    key = row_key(id_col, text_col)
    full = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), key["id"].alias("id"), key["hash"].alias("hash"), F.lit(1).alias("copy"), F.col(source_col).cast("string").alias("source"), word_count(F.col(text_col)).alias("size"))
    if not rows.filter("key.copy > 1").isEmpty():  # number repeated rows as the plan did
        full = full.withColumn("copy", F.row_number().over(Window.partitionBy("id", "hash").orderBy("source", "size")))
    met = full.join(plan, F.col("id").eqNullSafe(F.col("key.id")) & (F.col("hash") == F.col("key.hash")) & (F.col("copy") == F.col("key.copy")))
    text_at = docs.columns.index(text_col)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in (whole.slice(at, PIECE_ROWS) for at in range(0, whole.num_rows, PIECE_ROWS)):
                cells = b.column(0).flatten()
                take, new = [], []
                for i, (text, n, some) in enumerate(zip(cells[text_at].to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True)):
                    take += [i] * n
                    new += [text] * n
                    if some:
                        spans = [m.span() for m in WORDS.finditer(text)]
                        for run in runs_of(some):
                            take.append(i)
                            new.append(text[spans[run[0]][0] : spans[run[1] - 1][1]])
                at = pa.array(take, pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(new, pa.string()) if j == text_at else c.take(at) for j, c in enumerate(cells)], docs_columns)

    docs_columns = docs.columns
    mixed = met.select("row", "passes", "pieces").mapInArrow(tidy(cut), docs.schema)
    if "n_chars" in docs_columns:
        mixed = mixed.withColumn("n_chars", F.length(text_col).cast(docs.schema["n_chars"].dataType))
    return mixed.sortWithinPartitions(F.xxhash64(id_col, text_col, F.lit(23)))


def runs_of(pieces: list[dict]) -> list[tuple[int, int]]:
    """Word ranges with adjacent blocks joined."""
    out: list[list[int]] = []
    for p in pieces:
        a, b = p["first"], p["first"] + p["words"]
        if out and out[-1][1] == a:
            out[-1][1] = b
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_counts(table(spark, sf_dir, "documents")).select(F.col("key.id").alias("doc_id"), "size", "source_size", "target", "taken")


def mix_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(source, source_size, target): what op6 aims at."""
    docs = table(spark, sf_dir, "documents")
    targets = targets_for(docs.select(F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("size")))
    return targets.select("source", "source_size", F.round("target", 4).alias("target"))


QUERIES = {"op6_mixing": op6_mixing, "mix_targets": mix_targets}
ORACLES = {
    # filled up to one level: sources whose cap lies below their weight's share of it stop at the cap
    "mix_targets": """
        WITH s AS (SELECT source, sum(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')))::BIGINT AS source_size FROM documents GROUP BY 1),
        w AS (SELECT *, [5, 2, 1][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1] AS weight, 2.0 * source_size AS cap FROM s),
        o AS (SELECT *, cap / weight AS full_at, 1.5 * sum(source_size) OVER () - coalesce(sum(cap) OVER below, 0) AS rest, sum(weight) OVER () - coalesce(sum(weight) OVER below, 0) AS open_weight
              FROM w WINDOW below AS (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        level AS (SELECT rest / open_weight AS height FROM o WHERE rest / open_weight <= full_at ORDER BY full_at, source NULLS LAST LIMIT 1)
        SELECT source, source_size, round(least(cap, weight * coalesce((SELECT height FROM level), 1e300)), 4) AS target FROM o""",
}
