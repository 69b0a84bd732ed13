"""Reach of many seeds at once, a world at a time, in graphs whose edges all go from lower to higher ids.

A coin is a function of (salt, rep, draw, edge_id) and not of the seed, so all seeds share a draw's world: its coins are
thrown once, and one walk from the highest node down gives every node's reached set.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadlab.functions.coins import MD5_BLOCK, key_of, md5_coins, mixed_coins

WORLD_BYTES = 256 << 20  # of one world's live edges, and of its reached sets


def shared_nodes(edges: DataFrame) -> np.ndarray | None:
    """The graph's nodes in order, where edges go up and a world fits a task; None otherwise."""
    if edges.count() * 8 > WORLD_BYTES or not edges.filter("src >= dst").isEmpty():
        return None
    nodes = edges.select(F.col("src").alias("node")).unionByName(edges.select(F.col("dst").alias("node"))).filter("node IS NOT NULL").distinct()
    if (size := nodes.count()) * size > 8 * WORLD_BYTES:
        return None
    return np.sort(nodes.toArrow()["node"].to_numpy().astype(np.int64))


def packed_edges(src: np.ndarray, dst: np.ndarray) -> bytes:
    """Edges in (src, dst) order as runs of src."""
    heads = np.flatnonzero(np.concatenate([[True], src[1:] != src[:-1]]))
    return np.concatenate([[len(heads)], src[heads], np.diff(np.append(heads, len(src))), dst]).astype(np.int32).tobytes()


def whole_world(packed: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(src, dst) of all packed edges, in order."""
    src, dst = [], []
    for x in sorted((np.frombuffer(x, np.int32) for x in packed), key=lambda x: (x[1], x[1 + 2 * x[0]])):
        k = int(x[0])
        src.append(np.repeat(x[1 : k + 1], x[k + 1 : 2 * k + 1]))
        dst.append(x[2 * k + 1 :])
    src, dst = np.concatenate(src), np.concatenate(dst)
    if ((src[1:] < src[:-1]) | (src[1:] == src[:-1]) & (dst[1:] < dst[:-1])).any():
        order = np.lexsort((dst, src))
        src, dst = src[order], dst[order]
    return src, dst


def reached_sets(src: np.ndarray, dst: np.ndarray, n: int) -> np.ndarray:
    """uint64[n, words]: bit b of word w of a row is set where the row's node reaches node 64 w + b, itself left out.

    A node's ends are taken from the lowest up; those that an earlier one reaches add nothing and are passed over.
    """
    out = np.zeros((n, -(-n // 64)), np.uint64)
    heads = np.flatnonzero(np.concatenate([[True], src[1:] != src[:-1]])) if len(src) else np.zeros(0, np.int64)
    one = np.uint64(1)
    for i, j in zip(heads[::-1].tolist(), [len(src), *heads[:0:-1].tolist()], strict=True):
        row, ends = out[src[i]], dst[i:j]
        word, bit = ends >> 6, (ends & 63).astype(np.uint64)
        while len(ends):
            np.bitwise_or(row, out[ends[0]], out=row)
            row[word[0]] |= one << bit[0]
            left = np.flatnonzero((row[word] >> bit & one) == 0)
            ends, word, bit = ends[left], word[left], bit[left]
    return out


def sums_over(sets: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Sum of the weights of each row's nodes."""
    rows = sets.view(np.uint8)
    weight = np.pad(weight, (0, 8 * rows.shape[1] - len(weight))).reshape(-1, 8)
    table = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.int64) @ weight.T
    at = np.arange(rows.shape[1])
    return np.concatenate([table[rows[i : i + 64], at].sum(1) for i in range(0, len(rows), 64)])


def spread_of_all(edges: DataFrame, nodes: np.ndarray, n: int, reps: int, salt: int, kind: str) -> DataFrame:
    """(node, rep, draw, reached, thrown) of every node with out-edges: nodes reached, itself left out, and coins thrown."""
    sc = edges.sparkSession.sparkContext
    degrees = edges.filter("dst IS NOT NULL").groupBy("src").agg(F.count(F.lit(1)).alias("out")).toArrow()
    degree = np.zeros(len(nodes), np.int64)
    degree[np.searchsorted(nodes, degrees["src"].to_numpy().astype(np.int64))] = degrees["out"].to_numpy()
    sent = sc.broadcast((nodes, degree))
    schema = pa.schema([("node", pa.int64()), ("rep", pa.int32()), ("draw", pa.int64()), ("reached", pa.int64()), ("thrown", pa.int64())])

    def live(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for b in batches:
            held.append(b)
            size += b.num_rows
            if size >= 2 * MD5_BLOCK:
                yield from thrown(held)
                held, size = [], 0
        if held:
            yield from thrown(held)

    def thrown(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(held)
        ids, src, dst, p = (rows[c].to_numpy() for c in ("edge_id", "src", "dst", "p"))
        src, dst = (np.searchsorted(sent.value[0], x) for x in (src, dst))
        order = np.lexsort((dst, src))
        ids, src, dst, p = ids[order], src[order], dst[order], p[order]
        for rep in range(reps):
            for draw in range(n):
                u = md5_coins(f"{salt}|{rep}|{draw}", ids) if kind == "md5" else mixed_coins(key_of(salt, rep, draw, "edge"), ids)
                some = np.flatnonzero(u < p)
                if len(some):
                    yield pa.RecordBatch.from_arrays([pa.array([rep * n + draw], pa.int64()), pa.array([packed_edges(src[some], dst[some])], pa.binary())], ["world", "packed"])
        # a world without a live edge is there too
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(reps * n)), pa.nulls(reps * n, pa.binary())], ["world", "packed"])

    def walk(world: int, packed: list[bytes]) -> Iterator[pa.RecordBatch]:
        known, out = sent.value
        sets = reached_sets(*whole_world(packed), len(known)) if packed else np.zeros((len(known), -(-len(known) // 64)), np.uint64)
        some = np.flatnonzero(out)
        reached = np.concatenate([np.bitwise_count(sets[i : i + 4096]).sum(1, dtype=np.int64) for i in range(0, len(sets), 4096)])
        spent = out + sums_over(sets, out)
        columns = [known[some], np.full(len(some), world // n, np.int32), np.full(len(some), world % n), reached[some], spent[some]]
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, packed = None, []
        for b in batches:
            for world, some in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if world != current:
                    if current is not None:
                        yield from walk(current, packed)
                    current, packed = world, []
                if some is not None:
                    packed.append(some)
        if current is not None:
            yield from walk(current, packed)

    columns = [F.col(c).cast("long").alias(c) for c in ("edge_id", "src", "dst")]
    tried = edges.filter("src IS NOT NULL AND dst IS NOT NULL").select(*columns, F.coalesce(F.col("p").cast("double"), F.lit(0.0)).alias("p"))
    dealt = tried.mapInArrow(live, "world long, packed binary").repartition(max(1, min(3 * reps * n, 4096)), "world").sortWithinPartitions("world")
    return dealt.mapInArrow(run, "node long, rep int, draw long, reached long, thrown long")
