"""Exact top-k by inner product with MaxScore pruning, shard by shard.

Candidates are dealt to shards of bounded size by a hash of their id; each shard gets the queries
in blocks and streams them over its index, so no task holds all queries and nothing that grows with
the data is broadcast. In a shard every dimension is split by sign into two posting lists, so a
list's largest impact times the query's weight bounds what a term can add. Every query brings a
threshold: its k-th score in one sample shard (of bounded size, sent to the queries). Terms whose
bounds sum to less than the threshold are non-essential: a vector outside all essential lists cannot
compete, and a shard whose terms are all non-essential is left unread. Essential lists are traversed,
survivors are probed in the remaining dimensions from the largest bound down; the threshold rises with
the k-th best of what the survivors have for sure, and those that cannot reach it are dropped. Scores
are 64-bit integers where their bound fits, Python integers elsewhere; equal scores go to the smaller
id. Shards' lists are merged by rank.

Defined cases: vectors that are null or hold null or non-finite components, or without id, take no
part; shorter vectors count as padded with zeros; rows that repeat id and vector count once; an id of
several vectors is a candidate by each, and as a query has one list of the best of all; with fewer than k candidates all are returned; a
score beyond a long is ranked by its whole value and reported as the long nearest to it; an empty table
gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadlab.llm.common import RowBuffer, bucket, table, tidy

SHARD_ROWS = 16_384
SAFE = float(1 << 62)
LONG = (-(1 << 63), (1 << 63) - 1)


def whole_numbers(values: np.ndarray) -> np.ndarray:
    """Whole doubles as 64-bit integers, or as Python integers where one is too large."""
    if not len(values) or np.abs(values).max() < SAFE:
        return values.astype(np.int64)
    return np.array([int(x) for x in values.tolist()], object)


def whole_key(score: int) -> str | None:
    """Text that sorts scores beyond a long among each other and around null; null for others."""
    if LONG[0] <= score <= LONG[1]:
        return None
    digits = str(abs(score))
    text = f"{len(digits):06d}{digits}"
    return "p" + text if score > 0 else "a" + text.translate(str.maketrans("0123456789", "9876543210"))


class Shard:
    """Sign-split postings of integer vectors."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray):
        order = np.lexsort((*rows.T[::-1], ids)) if rows.shape[1] and rows.dtype != object else np.argsort(ids, kind="stable")
        ids, rows = ids[order], rows[order]
        keep = np.ones(len(ids), bool)
        keep[1:] = (ids[1:] != ids[:-1]) | (rows[1:] != rows[:-1]).any(1)
        self.ids, self.rows = ids[keep], rows[keep]
        self.by_dim = np.ascontiguousarray(self.rows.T)
        self.most, self.least = (self.rows.max(0), self.rows.min(0)) if len(self.ids) else (np.zeros(rows.shape[1], np.int64),) * 2
        self.postings = {(d, s): np.flatnonzero(c > 0 if s > 0 else c < 0) for d, c in enumerate(self.by_dim) for s in (1, -1)}

    def best(self, own_id: int, query: np.ndarray, k: int, threshold: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of the k best rows other than the query's own; those below ``threshold`` may be left out."""
        width = min(len(query), self.rows.shape[1])
        q, most, least, by_dim = query[:width], self.most[:width], self.least[:width], self.by_dim
        if by_dim.dtype != object and np.abs(q.astype(float)) @ np.maximum(np.abs(most.astype(float)), np.abs(least.astype(float))) >= SAFE:
            by_dim = by_dim.astype(object)
        if by_dim.dtype == object:
            q, most, least = q.astype(object), most.astype(object), least.astype(object)
        n = len(self.ids)
        terms = np.flatnonzero(q)
        ends = np.stack([q * most, q * least]) if width else np.zeros((2, 0), np.int64)
        gains, losses = np.maximum(ends.max(0), 0)[terms], np.minimum(ends.min(0), 0)[terms]
        rising = np.argsort(gains, kind="stable")
        terms = terms[rising]
        below = np.concatenate([[0], np.cumsum(gains[rising])])  # below[i]: most that the i weakest terms add
        above = np.concatenate([[0], np.cumsum(losses[rising])])  # and least
        if threshold is not None and below[-1] < threshold:
            return self.ids[:0], np.zeros(0, np.int64)
        # terms[:split] are non-essential; a row that is in no essential list scores what they add, or less
        split = 0 if threshold is None else max(0, int(np.searchsorted(below, threshold, "left")) - 1)
        if split:
            touched = np.zeros(n, bool)
            for d in terms[split:][::-1]:
                touched[self.postings[int(d), 1 if q[d] > 0 else -1]] = True
                if touched.all():
                    break
            rows = np.flatnonzero(touched)
        else:
            rows = np.arange(n)
        rows = rows[self.ids[rows] != own_id]
        partial = np.zeros(len(rows), by_dim.dtype)
        for i in range(len(terms) - 1, -1, -1):
            d = terms[i]
            partial = partial + q[d] * by_dim[d][rows]
            if i and i % 8 == 0 and len(rows) > k:
                sure = np.partition(partial, len(rows) - k)[len(rows) - k] + above[i]
                threshold = sure if threshold is None else max(threshold, sure)
                alive = partial + below[i] >= threshold
                if not alive.all():
                    rows, partial = rows[alive], partial[alive]
        order = np.lexsort((self.ids[rows], -partial))[:k] if partial.dtype != object else np.array(sorted(range(len(rows)), key=lambda j: (-partial[j], self.ids[rows[j]]))[:k], np.int64)
        return self.ids[rows[order]], partial[order]


def rows_of(lists: list[np.ndarray]) -> np.ndarray:
    """Vectors as rows of whole numbers, filled up with zeros."""
    width = max(map(len, lists), default=0)
    out = np.zeros((len(lists), width))
    for j, v in enumerate(lists):
        out[j, : len(v)] = v
    return whole_numbers(out.ravel()).reshape(out.shape)


def vectors_of(b: pa.RecordBatch, column: int) -> list[np.ndarray]:
    lists = b.column(column)
    flat, offsets = lists.values.to_numpy(zero_copy_only=False), lists.offsets.to_numpy()
    return [flat[x:y] for x, y in zip(offsets, offsets[1:], strict=False)]


def exact_top_k(queries: DataFrame, vectors: DataFrame, k: int = 10, id_col: str = "vec_id", vector_col: str = "vector", shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k best vectors (arrays of whole doubles) by inner product."""
    clean = lambda df: df.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("v")).filter(F.col("id").isNotNull() & F.col("v").isNotNull() & ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf")))))
    base, asked = clean(vectors), clean(queries).dropDuplicates(["id", "v"])
    shards = max(1, -(-base.count() // shard_rows))
    dealt = base.select(bucket(F.col("id"), 7, shards).alias("shard"), F.lit(0).alias("kind"), "id", "v", F.lit(None).cast("string").alias("threshold"))
    if shards > 1:
        asked = with_thresholds(asked, dealt.filter("shard = 0").select("id", "v"), k)
    else:
        asked = asked.withColumn("threshold", F.lit(None).cast("string"))
    sent = asked.select(F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), F.lit(1).alias("kind"), "id", "v", "threshold")
    both = dealt.unionByName(sent.withColumn("shard", F.col("shard").cast("int"))).repartition(shards, "shard").sortWithinPartitions("shard", "kind", "id")
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64()), ("whole", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, held_ids, held, index = None, [], [], None
        out = RowBuffer(schema)
        for b in batches:
            shard, kind, ids = (b.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            thresholds = b.column(4).to_pylist()
            for i, row in enumerate(vectors_of(b, 3)):
                if shard[i] != current:
                    current, held_ids, held, index = shard[i], [], [], None
                if kind[i] == 0:
                    held_ids.append(ids[i])
                    held.append(row)
                    continue
                if index is None:
                    index, held_ids, held = Shard(np.asarray(held_ids, np.int64), rows_of(held)), [], []
                found, scores = index.best(ids[i], whole_numbers(row), k, None if thresholds[i] is None else int(thresholds[i]))
                for vec_id, score in zip(found.tolist(), scores.tolist(), strict=True):
                    if out.add(int(ids[i]), vec_id, min(max(score, LONG[0]), LONG[1]), whole_key(score)):
                        yield out.take()
        if len(out):
            yield out.take()

    partial = both.mapInArrow(tidy(run), "query_id long, vec_id long, score long, whole string")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), F.desc(F.coalesce("whole", F.lit("m"))), "vec_id")
    return partial.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def with_thresholds(asked: DataFrame, sample: DataFrame, k: int) -> DataFrame:
    """asked(id, v) + threshold: the k-th score in one shard, which any answer has to reach (null: fewer than k rows there)."""
    rows = sample.toPandas()  # one shard: about SHARD_ROWS rows at any size of the table
    index = Shard(rows["id"].to_numpy(np.int64), rows_of([np.asarray(v, float) for v in rows["v"]]))
    sent = asked.sparkSession.sparkContext.broadcast(index)
    schema = pa.schema([("id", pa.int64()), ("v", pa.list_(pa.float64())), ("threshold", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            least = []
            for own, row in zip(b.column(0).to_pylist(), vectors_of(b, 1), strict=True):
                _, scores = sent.value.best(own, whole_numbers(row), k)
                least.append(str(scores.tolist()[-1]) if len(scores) == k else None)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(least, pa.string())], schema=schema)

    return asked.mapInArrow(tidy(run), "id long, v array<double>, threshold string")


def scaled_integers(df: DataFrame, factor: int, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(vec_id, vector): floor(factor * x) of every component, as whole doubles; vectors with bad components become null.

    From 2 ** 52 on a double is whole already; a product beyond a double's range counts as non-finite.
    """
    bad = F.exists(vector_col, lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == F.lit(float("inf"))))

    def whole(x):
        y = F.lit(float(factor)) * x.cast("double")
        return F.when(F.abs(y) < float(1 << 52), F.floor(y).cast("double")).otherwise(y)

    return df.select(F.col(id_col).alias("vec_id"), F.when(F.col(vector_col).isNotNull() & ~bad, F.transform(vector_col, whole)).alias("vector"))


def op2_maxscore(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = scaled_integers(table(spark, sf_dir, "embeddings"), 1024)
    return exact_top_k(vectors.filter(F.col("vec_id") % 100 == 0), vectors)


QUERIES = {"op2_maxscore": op2_maxscore}
ORACLES = {
    "op2_maxscore": """
        WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS a FROM embeddings
                   WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
        e AS (SELECT vec_id, unnest(a) AS c, generate_subscripts(a, 1) AS d FROM v),
        s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(sum(q.c * c.c) AS BIGINT) AS score
              FROM e q JOIN e c ON q.d = c.d AND q.vec_id <> c.vec_id WHERE q.vec_id % 100 = 0 GROUP BY 1, 2),
        r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
        SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10""",
}
