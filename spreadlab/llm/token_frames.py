"""Token-ID files: independent zstandard frames, a trailing seek table and per-frame checksums.

File layout (the public seekable zstandard layout): data frames, each a complete zstandard frame
over the little-endian unsigned 32-bit ids of whole documents, then one skippable frame holding
the seek table (compressed size, decompressed size, checksum of each frame) and its footer.
A reader that wants some documents decompresses only the frames they lie in.

Defined cases: a null or empty text is the end id alone; repeated rows are repeated documents, in
text order within a doc_id; a null doc_id sorts first; an empty table gives no files and no rows;
other columns are ignored. A special literal of the vocabulary inside a text is that special id, as
the library's plain call gives it.
"""

from __future__ import annotations

import re
import struct
from codecs import charmap_decode
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spreadlab.llm.common import RowBuffer, arrow_rows, open_fs, table, tidy
from spreadlab.storage import materialize, scratch_path

# Fixed values of the seekable layout.
SKIPPABLE_MAGIC = 0x184D2A5E
SEEK_MAGIC = 0x8F92EAB1
CHECKSUM_FLAG = 0x80
FRAME_BYTES = 256 << 10
MEMO_BYTES = 40 << 20  # of each of a memo's two generations
ENTRY_BYTES = 140  # what an entry takes besides its characters

# A byte-level vocabulary writes each byte as a character: printable ones as themselves, the rest from U+0100 on.
_PRINTED = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
BYTE_LETTERS = {b: 0x100 + i for i, b in enumerate(b for b in range(256) if b not in _PRINTED)}
_LETTERS = "A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f"
SPACE_LETTER = chr(BYTE_LETTERS[0x20])
SPELLING = "".join(chr(BYTE_LETTERS.get(b, b)) for b in range(256))
KNOWN_LETTERS = re.compile(f" ?[{_LETTERS}]+").fullmatch
MARKS = ".,;:!?|#$%&*()+/=-"
_MARKS = f"[{MARKS}]+"
PLAIN_SEGMENT = re.compile(f" ?[{_LETTERS}]+(?:{_MARKS}|\n(?=[{_LETTERS}])|[{_LETTERS}]+)+").fullmatch
PLAIN_TOKENS = re.compile(f" ?[{_LETTERS}]+|{_MARKS}|\n").findall
# Words of known letters before a space, a newline, a mark or the end; marks before a space, a newline, a known letter or the
# end; newlines before a known letter: each is one pre-token wherever it stands. Else the rest up to a space is one piece.
PIECES = re.compile(f" ?[{_LETTERS}]++(?=[ \n{re.escape(MARKS)}]|\\Z)|{_MARKS}+(?=[ \n{_LETTERS}]|\\Z)|\n(?=[{_LETTERS}])| ?[^ ]++").findall
OTHER_SPACES = [chr(c) for c in range(0x3001) if chr(c).isspace() and c != 0x20]

MANIFEST = T.StructType([T.StructField("part", T.IntegerType()), T.StructField("path", T.StringType()), T.StructField("docs", T.LongType()), T.StructField("ids", T.LongType())])


def has_odd_space(text: str) -> bool:
    """Whether a space stands at an end or next to white space; plain searches, since most texts hold few kinds of it."""
    if text[:1] == " " or text[-1:] == " " or "  " in text:
        return True
    return any(c in text and (f" {c}" in text or f"{c} " in text) for c in OTHER_SPACES)


_PACKERS = [struct.Struct(f"<{n}I").pack for n in range(33)]


def packed_ids(ids: list[int]) -> bytes:
    """Little-endian unsigned 32-bit integers."""
    return _PACKERS[len(ids)](*ids) if len(ids) < len(_PACKERS) else struct.pack(f"<{len(ids)}I", *ids)


class SegmentEncoder(dict):
    """Encodes texts through the tokenizers library, remembering segments that it has met.

    A text is cut only at a single ASCII space between two characters that are not white space. No
    pre-token spans such a place, so the segments' ids in a row are the whole text's ids. A text that
    holds one of the vocabulary's special literals goes to the library whole.

    The memo is bounded by bytes: when the young generation is full it becomes the old one, and
    what is met again moves back, so common segments stay.
    """

    def __init__(self, path: str):
        super().__init__()
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.tokenize = self.model.tokenize
        self.old: dict[str, bytes] = {}
        self.held = 0
        specials = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.special = re.compile("|".join(map(re.escape, specials))).search if specials else None

    def __missing__(self, segment: str) -> bytes:
        if (known := self.old.get(segment)) is not None:
            return self.keep(segment, known)
        if KNOWN_LETTERS(segment):  # one pre-token: the model alone encodes it
            spelt = segment.replace(" ", SPACE_LETTER) if segment.isascii() else charmap_decode(segment.encode(), "strict", SPELLING)[0]
            return self.keep(segment, packed_ids([t.id for t in self.tokenize(spelt)]))
        head = segment.rstrip(MARKS)
        if len(head) < len(segment) and KNOWN_LETTERS(head):  # the commonest plain segment: a word and its marks
            return self[head] + self[segment[len(head) :]]
        if PLAIN_SEGMENT(segment):
            return b"".join([self[t] for t in PLAIN_TOKENS(segment)])
        return self.keep(segment, packed_ids(self.tokenizer.encode(segment, add_special_tokens=False).ids))

    def keep(self, segment: str, ids: bytes) -> bytes:
        if len(segment) <= 64:
            self.held += len(segment) + len(ids) + ENTRY_BYTES
            if self.held >= MEMO_BYTES:
                self.old, self.held = dict(self), 0
                self.clear()
            self[segment] = ids
        return ids

    def encode(self, text: str) -> bytes:
        if self.special is not None and self.special(text):
            return packed_ids(self.tokenizer.encode(text, add_special_tokens=False).ids)
        if not has_odd_space(text):
            return b"".join(map(self.__getitem__, PIECES(text)))
        pieces = text.split(" ")
        segments, held = [], pieces[0]
        for before, p in zip(pieces, pieces[1:], strict=False):
            if before and p and not before[-1].isspace() and not p[0].isspace():
                segments.append(held)
                held = " " + p
            else:
                held += " " + p
        segments.append(held)
        return b"".join(map(self.__getitem__, segments))


@lru_cache(maxsize=2)
def encoder(path: str) -> SegmentEncoder:
    return SegmentEncoder(path)


class FrameWriter:
    """Writes ids of whole documents as frames, then the seek table."""

    def __init__(self, sink, level: int = 3):
        self.sink, self.compressor = sink, zstandard.ZstdCompressor(level=level, write_checksum=True)
        self.held, self.held_bytes, self.entries = [], 0, []

    def add(self, ids: bytes) -> tuple[int, int]:
        """Frame and byte offset where the document begins."""
        at = (len(self.entries), self.held_bytes)
        self.held.append(ids)
        self.held_bytes += len(ids)
        if self.held_bytes >= FRAME_BYTES:
            self.flush()
        return at

    def flush(self) -> None:
        if self.held:
            raw = b"".join(self.held)
            packed = self.compressor.compress(raw)
            self.sink.write(packed)
            self.entries.append((len(packed), len(raw), xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF))
            self.held, self.held_bytes = [], 0

    def finish(self) -> None:
        self.flush()
        seek = b"".join(struct.pack("<III", *e) for e in self.entries) + struct.pack("<IBI", len(self.entries), CHECKSUM_FLAG, SEEK_MAGIC)
        self.sink.write(struct.pack("<II", SKIPPABLE_MAGIC, len(seek)) + seek)


def read_seek_table(source) -> list[tuple[int, int, int, int]]:
    """(offset, compressed, decompressed, checksum) of each frame of a seekable file."""
    size = source.size()
    source.seek(size - 9)
    n, flags, magic = struct.unpack("<IBI", source.read(9))
    if magic != SEEK_MAGIC or flags != CHECKSUM_FLAG:
        raise ValueError("no seek table at the end of the file")
    source.seek(size - 9 - 12 * n)
    sizes = np.frombuffer(source.read(12 * n), "<u4").reshape(n, 3).astype(np.int64)
    starts = np.concatenate([[0], np.cumsum(sizes[:, 0])[:-1]]) if n else np.zeros(0, np.int64)
    return [(int(a), *map(int, s)) for a, s in zip(starts, sizes, strict=True)]


def read_frame(source, entry: tuple[int, int, int, int]) -> bytes:
    """One frame's ids, checked against the seek table."""
    offset, packed, size, checksum = entry
    source.seek(offset)
    raw = zstandard.ZstdDecompressor().decompressobj().decompress(source.read(packed))
    if len(raw) != size or xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != checksum:
        raise ValueError("a frame does not match its checksum")
    return raw


def write_token_files(docs: DataFrame, tokenizer_path: str, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """Encode every text and write the files in ascending id order; returns (files, index).

    files: part, path, docs, ids. index: part, nth, id, frame, offset (bytes in the frame), before (ids of
    the file's documents before this one), n_tokens.
    Each task writes a file of its own attempt; only files of attempts that ended are in the index.
    """
    spark = docs.sparkSession
    folder = scratch_path(spark, "tokens")
    index_schema = pa.schema([("part", pa.int32()), ("path", pa.string()), ("nth", pa.int64()), ("id", pa.int64()), ("frame", pa.int32()), ("offset", pa.int64()), ("before", pa.int64()), ("n_tokens", pa.int64())])
    end = struct.pack("<I", end_id)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task = TaskContext.get()
        fs, base = open_fs(folder)
        encode, sink, nth, before = encoder(tokenizer_path).encode, None, 0, 0
        out = RowBuffer(index_schema)
        for doc_id, text in arrow_rows(batches, "id", "text"):
            if sink is None:
                path = f"part-{task.partitionId():06d}-{task.taskAttemptId()}.ids.zst"
                fs.create_dir(base, recursive=True)
                sink = fs.open_output_stream(f"{base}/{path}", compression=None)
                writer = FrameWriter(sink)
            ids = (encode(text) if text else b"") + end
            frame, offset = writer.add(ids)
            if out.add(task.partitionId(), path, nth, doc_id, frame, offset, before, len(ids) // 4):
                yield out.take()
            nth, before = nth + 1, before + len(ids) // 4
        if sink is not None:
            writer.finish()
            sink.close()
        if len(out):
            yield out.take()

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    ordered = rows.repartitionByRange(F.col("id")).sortWithinPartitions("id", "text")
    index = materialize(ordered.mapInArrow(tidy(write), "part int, path string, nth long, id long, frame int, offset long, before long, n_tokens long"), "token-index")
    files = index.groupBy("part", "path").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_tokens").alias("ids")).withColumn("path", F.concat(F.lit(folder + "/"), "path"))
    return files.select("part", "path", "docs", "ids"), index


def read_token_files(files: DataFrame, index: DataFrame) -> DataFrame:
    """Documents read back from the files: id, start (ids of all documents before), ids (binary), n_tokens.

    One row per frame to read goes to the tasks, so a subset of the index opens only its frames; ``files``
    is always the whole list, for it tells how many ids lie before each file.
    """
    from pyspark.sql import Window

    bases = files.select("part", F.col("path").alias("file"), (F.sum("ids").over(Window.orderBy("part")) - F.col("ids")).alias("base"))
    frames = index.groupBy("part", "frame").agg(F.sort_array(F.collect_list(F.struct("offset", "nth", "before", "id", "n_tokens"))).alias("docs"))
    wanted = frames.join(bases, "part").select("file", "frame", "base", "docs")
    schema = pa.schema([("id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids", pa.binary())])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        opened, source = None, None
        out = RowBuffer(schema)
        for file, frame, base, docs in arrow_rows(batches, "file", "frame", "base", "docs"):
            if file != opened:
                if source is not None:
                    source.close()
                fs, path = open_fs(file)
                opened, source = file, fs.open_input_file(path)
                seek = read_seek_table(source)
            raw = read_frame(source, seek[frame])
            for d in docs:
                ids = raw[d["offset"] : d["offset"] + 4 * d["n_tokens"]]
                if out.add(d["id"], base + d["before"], d["n_tokens"], ids, weight=len(ids)):
                    yield out.take()
        if source is not None:
            source.close()
        if len(out):
            yield out.take()

    return wanted.mapInArrow(tidy(read), "id long, start long, n_tokens long, ids binary")


def token_digest(docs: DataFrame, tokenizer_path: str | None = None, end_id: int = 2) -> DataFrame:
    """Write the token files of ``docs``, read them back and digest each document's ids."""
    if tokenizer_path is None:
        import public_tokenizers

        tokenizer_path = public_tokenizers.path("byte_bpe_50k.json")
    back = read_token_files(*write_token_files(docs, tokenizer_path, end_id))
    return back.select(F.col("id").alias("doc_id"), "start", "n_tokens", F.crc32("ids").cast("long").alias("ids_crc32"))


def op10_token_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_digest(table(spark, sf_dir, "documents"))


QUERIES = {"op10_token_frames": op10_token_frames}

