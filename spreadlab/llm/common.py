"""Small helpers that the training-data operators share."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.fs as pafs
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

import numpy as np

PIECE_ROWS = 256
WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def ascii_lower(c: Column) -> Column:
    """A-Z only, the same in every locale."""
    return F.translate(c, UPPER, LOWER)


def words_of(text: str | None) -> list[bytes]:
    """UTF-8 words of a text; bytes.split() cuts at space and \\x09-\\x0D only, which is WORD's complement."""
    return [] if text is None else text.encode("utf-8", "surrogatepass").split()


def lower_words_of(text: str | None) -> list[bytes]:
    """As words_of after lower-casing A-Z (bytes.lower() leaves all other bytes alone)."""
    return [] if text is None else text.encode("utf-8", "surrogatepass").lower().split()


def hash_words(words: list[bytes]) -> np.ndarray:
    """64-bit hash of each word."""
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def mix64(h: np.ndarray) -> np.ndarray:
    """Bijective finaliser on 64-bit values."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def shingle_hashes(word_hashes: np.ndarray, k: int) -> np.ndarray:
    """Hash of every run of k words, in text order; a shorter non-empty text is one shingle of all its words."""
    n = len(word_hashes)
    if n == 0:
        return word_hashes
    width = min(k, n)
    out = np.full(n - width + 1, width, np.uint64)
    for i in range(width):
        out = mix64(out * np.uint64(0x9E3779B97F4A7C15) + word_hashes[i : n - width + 1 + i])
    return out


def bucket(c: Column, salt: int, n: int) -> Column:
    """Hash bucket in [0, n) that depends on the key alone."""
    return F.pmod(F.xxhash64(c, F.lit(salt)), F.lit(n)).cast("int")


def open_fs(uri: str) -> tuple[pafs.FileSystem, str]:
    """File system and path of a shared folder, for code on executors (file, hdfs, s3, gs...)."""
    if "://" not in uri and not uri.startswith("file:"):
        return pafs.LocalFileSystem(), uri
    if uri.startswith("file:"):
        return pafs.LocalFileSystem(), "/" + uri.removeprefix("file:").lstrip("/")
    return pafs.FileSystem.from_uri(uri)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def partitions_for(df: DataFrame) -> int:
    """Shuffle width of the session as given."""
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def arrow_rows(batches: Iterator[pa.RecordBatch], *names: str) -> Iterator[tuple]:
    """Rows of Arrow batches as tuples of Python values, some hundred at a time, so that few texts are held twice."""
    for b in batches:
        for at in range(0, b.num_rows, PIECE_ROWS):
            part = b.slice(at, PIECE_ROWS)
            yield from zip(*(part.column(part.schema.get_field_index(n)).to_pylist() for n in names), strict=True)


def tidy(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``run``, which hands its freed memory back when it ends: workers are reused by later stages."""

    def tidied(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        try:
            ctypes.CDLL(None).malloc_trim(0)
        except (AttributeError, OSError):  # not this C library
            return

    return tidied


class RowBuffer:
    """Collects output rows and hands them out as Arrow batches of bounded size."""

    def __init__(self, schema: pa.Schema, rows: int = 20_000, weight: int = 8 << 20):
        self.schema, self.limit, self.weight = schema, rows, weight
        self.columns: list[list] = [[] for _ in schema]
        self.heavy = 0

    def add(self, *row: object, weight: int = 0) -> bool:
        """True if the buffer is due to be emptied."""
        for column, value in zip(self.columns, row, strict=True):
            column.append(value)
        self.heavy += weight
        return len(self.columns[0]) >= self.limit or self.heavy >= self.weight

    def take(self) -> pa.RecordBatch:
        out = pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(self.columns, self.schema, strict=True)], schema=self.schema)
        self.columns = [[] for _ in self.schema]
        self.heavy = 0
        return out

    def __len__(self) -> int:
        return len(self.columns[0])
