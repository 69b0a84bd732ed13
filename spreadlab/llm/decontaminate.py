"""Benchmark decontamination: rare n-gram seeds, then Smith-Waterman alignment.

Seeds are word n-grams of the test items. Their document frequency is counted over the whole corpus
and each item keeps its rarest share (never fewer than ``least_seeds``), so an item whose copies
are everywhere still has seeds. A document that holds a seed is aligned with the item in a window
around each seed; the best local score over a perfect copy's score is the contamination score.

Items travel to the tasks in blocks of a bounded number of words; a larger benchmark takes more
passes. Documents are never shuffled, and a document's text is read whole.

Defined cases: null or empty texts hold nothing and empty items match nothing; an item shorter than
a seed is its own seed; repeated rows are judged each; a null id is judged like any other; a
repeated item_id counts each of its texts; an empty table gives no rows.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadlab.llm.common import RowBuffer, arrow_rows, bucket, hash_words, lower_words_of, shingle_hashes, table, tidy
from spreadlab.storage import materialize

SEED_WORDS = 3
BLOCK_WORDS = 1_000_000
MATCH, MISMATCH, GAP = 2, -1, -1
LEAST_SCORE = 0.5


def align(item: np.ndarray, window: np.ndarray) -> tuple[int, int, int]:
    """Best Smith-Waterman score of two word-hash arrays, and the window's aligned range."""
    width = len(window)
    ramp = -GAP * np.arange(width + 1)
    above, best, end = np.zeros(width + 1, np.int64), 0, (0, 0)
    came = np.arange(width + 1)  # where the alignment that ends here began
    for i, word in enumerate(item):
        diagonal = above[:-1] + np.where(window == word, MATCH, MISMATCH)
        down = above[1:] + GAP
        score = np.concatenate([[0], np.maximum(np.maximum(diagonal, down), 0)])
        start = np.concatenate([[0], np.where(diagonal >= down, came[:-1], came[1:])])
        start = np.where(score > 0, start, np.arange(width + 1))
        # gaps along the row: running maximum of score + ramp
        lifted = np.maximum.accumulate(score + ramp)
        source = np.maximum.accumulate(np.where(score + ramp == lifted, np.arange(width + 1), 0))
        above, came = lifted - ramp, start[source]
        top = int(above.argmax())
        if above[top] > best:
            best, end = int(above[top]), (int(came[top]), top)
    return best, end[0], end[1]


class Items:
    """A block of test items with their seeds."""

    def __init__(self, rows: list[tuple[int, str | None]]):
        self.ids, self.words = [], []
        for item_id, text in rows:
            words = hash_words(lower_words_of(text))
            if len(words):
                self.ids.append(item_id)
                self.words.append(words)
        seeds = [shingle_hashes(w, SEED_WORDS) for w in self.words]
        self.seed_of = np.unique(np.concatenate(seeds)) if seeds else np.zeros(0, np.uint64)
        self.seeds = [np.searchsorted(self.seed_of, s) for s in seeds]
        self.places: dict[int, list[tuple[int, int]]] = {}

    def choose(self, frequency: np.ndarray, share: float, least_seeds: int) -> None:
        """Keep each item's rarest seeds; seeds that the corpus lacks cost nothing."""
        places = defaultdict(list)
        for item, seeds in enumerate(self.seeds):
            present = np.flatnonzero(frequency[seeds] > 0)
            rarest = present[np.argsort(frequency[seeds][present], kind="stable")]
            for at in rarest[: max(least_seeds, int(np.ceil(share * len(rarest))))]:
                places[int(seeds[at])].append((item, int(at)))
        self.places = dict(places)

    def present(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions and seed numbers of seeds in a text."""
        if not len(words) or not len(self.seed_of):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        h = shingle_hashes(words, SEED_WORDS)
        at = np.minimum(np.searchsorted(self.seed_of, h), len(self.seed_of) - 1)
        where = np.flatnonzero(self.seed_of[at] == h)
        return where, at[where]

    def leaks(self, text: str | None, least: float) -> list[tuple[int, float, int, int]]:
        """(item_id, score, start, end) of the items that the text holds, ranges in words."""
        words = hash_words(lower_words_of(text))
        found: dict[int, list[int]] = defaultdict(list)
        for where, seed in zip(*(x.tolist() for x in self.present(words)), strict=True):
            for item, at in self.places.get(seed, ()):
                found[item].append(where - at)
        out = []
        for item, offsets in found.items():
            target = self.words[item]
            n, best = len(target), (0, 0, 0)
            slack = max(4, n // 2)
            reached = -1
            for offset in sorted(set(offsets)):
                if offset + n + slack <= reached:
                    continue
                low, high = max(0, offset - slack), min(len(words), offset + n + slack)
                if 0 <= offset and offset + n <= len(words) and np.array_equal(words[offset : offset + n], target):
                    got = (MATCH * n, offset, offset + n)  # the highest score there is
                else:
                    score, a, b = align(target, words[low:high])
                    got = (score, low + a, low + b)
                if got[0] > best[0]:
                    best = got
                if best[0] == MATCH * n:
                    break
                reached = high if offset + slack // 2 >= reached - n else reached
            if best[0] >= least * MATCH * n:
                out.append((self.ids[item], best[0] / (MATCH * n), best[1], best[2]))
        return out


def item_blocks(docs: DataFrame, benchmark: DataFrame, share: float, least_seeds: int, item_col: str, item_text_col: str) -> Iterator[Items]:
    """Blocks of items, each with its seeds chosen by their frequency over all of ``docs(text)``."""
    items = benchmark.select(F.col(item_col).cast("long").alias("item_id"), F.col(item_text_col).cast("string").alias("text"))
    total = items.agg(F.sum(F.length("text"))).collect()[0][0] or 0
    n_blocks = max(1, -(-total // (6 * BLOCK_WORDS)))
    for block in range(n_blocks):
        rows = items.filter(bucket(F.coalesce("item_id", F.lit(-1)), 43, n_blocks) == block).orderBy("item_id", "text").collect()
        found = Items([(r.item_id, r.text) for r in rows])
        sent = docs.sparkSession.sparkContext.broadcast(found)

        def count(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            some, total_ = sent.value, None
            for (text,) in arrow_rows(batches, "text"):
                _, seeds = some.present(hash_words(lower_words_of(text)))
                if len(seeds):
                    total_ = np.zeros(len(some.seed_of), np.int64) if total_ is None else total_
                    total_[np.unique(seeds)] += 1
            if total_ is not None:
                at = np.flatnonzero(total_)
                yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total_[at], pa.int64())], ["seed", "n"])

        counted = docs.select("text").mapInArrow(tidy(count), "seed long, n long").groupBy("seed").agg(F.sum("n").alias("n")).toPandas()
        frequency = np.zeros(len(found.seed_of), np.int64)
        frequency[counted["seed"].to_numpy(np.int64)] = counted["n"].to_numpy(np.int64)
        found.choose(frequency, share, least_seeds)
        yield found


def find_leaks(docs: DataFrame, benchmark: DataFrame, least: float = LEAST_SCORE, share: float = 0.75, least_seeds: int = 8, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """(id, item_id, score, start_word, end_word) of every document and item that it holds a copy of."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    schema = pa.schema([("id", pa.int64()), ("item_id", pa.int64()), ("score", pa.float64()), ("start_word", pa.int64()), ("end_word", pa.int64())])
    out = None
    for items in item_blocks(rows, benchmark, share, least_seeds, item_col, item_text_col):
        sent = docs.sparkSession.sparkContext.broadcast(items)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            buffer = RowBuffer(schema)
            for doc_id, text in arrow_rows(batches, "id", "text"):
                for leak in sent.value.leaks(text, least):
                    if buffer.add(doc_id, *leak):
                        yield buffer.take()
            if len(buffer):
                yield buffer.take()

        found = rows.mapInArrow(tidy(run), "id long, item_id long, score double, start_word long, end_word long")
        out = found if out is None else out.unionByName(found)
    return out


def drop_leaks(docs: DataFrame, benchmark: DataFrame, least: float = LEAST_SCORE, share: float = 0.75, least_seeds: int = 8, text_col: str = "text") -> DataFrame:
    """Rows of ``docs`` that hold no copy of a test item; nothing is shuffled."""
    texts = docs.select(F.col(text_col).cast("string").alias("text"))
    for items in item_blocks(texts, benchmark, share, least_seeds, "item_id", "text"):
        sent = docs.sparkSession.sparkContext.broadcast(items)

        def keep(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            for b in batches:
                yield b.filter(pa.array([not sent.value.leaks(t, least) for (t,) in arrow_rows([b], text_col)], pa.bool_()))

        docs = docs.mapInArrow(tidy(keep), docs.schema)
    return docs


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return materialize(found, "leaks").select(F.col("id").alias("doc_id"), "item_id", "score", "start_word", "end_word")


QUERIES = {"op9_decontaminate": op9_decontaminate}
