"""WARC archives: one gzip member per record, read back by a sequential reader.

The reader decompresses incrementally, cuts records by their content length and checks every
payload digest; a broken digest or a cut-off record raises an error.

Defined cases: a null html is an empty payload; payloads below the least size are always
responses; a row without page_id is a response that no other refers to; rows that repeat the
smallest page_id of a payload are responses too; an empty table gives no archive and no rows.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadlab.llm.common import RowBuffer, arrow_rows, open_fs, table, tidy
from spreadlab.storage import materialize, scratch_path

CHUNK = 256 << 10
DATE = "2024-01-01T00:00:00Z"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"  # fixed value of the format


def urn(page_id: int | None) -> str:
    return f"<urn:page:{'' if page_id is None else page_id}>"


def from_urn(value: str) -> int | None:
    inner = value.removeprefix("<urn:page:").removesuffix(">")
    return int(inner) if inner else None


def one_line(url: str | None) -> str:
    """A header value cannot hold line ends."""
    return "" if url is None else url.replace("\r", "%0D").replace("\n", "%0A")


def record_bytes(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One record: a response with its payload, or a revisit that has the HTTP head only."""
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    revisit = refers_to is not None
    block = head if revisit else head + payload
    fields = [
        ("WARC-Type", "revisit" if revisit else "response"),
        ("WARC-Record-ID", urn(page_id)),
        ("WARC-Date", DATE),
        ("WARC-Target-URI", one_line(url)),
        ("WARC-Payload-Digest", f"sha256:{digest}"),
        *([("WARC-Refers-To", urn(refers_to)), ("WARC-Profile", REVISIT_PROFILE)] if revisit else []),
        ("Content-Type", "application/http; msgtype=response"),
        ("Content-Length", str(len(block))),
    ]
    return b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields).encode("utf-8", "surrogatepass") + b"\r\n" + block + b"\r\n\r\n"


def gzip_member(record: bytes, level: int = 6) -> bytes:
    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
    return packer.compress(record) + packer.flush()


def members(source) -> Iterator[bytes]:
    """Decompressed gzip members of a stream, one after another, reading bounded chunks."""
    pending = source.read(CHUNK)
    while pending:
        unpacker, parts = zlib.decompressobj(31), []
        while not unpacker.eof:
            if not pending:
                raise ValueError("the archive ends within a record")
            parts.append(unpacker.decompress(pending))
            pending = unpacker.unused_data if unpacker.eof else source.read(CHUNK)
        yield b"".join(parts)
        pending = pending or source.read(CHUNK)


def headers_of(block: bytes) -> tuple[dict[str, str], int]:
    """Header fields (lower-case names) and the offset of what follows them."""
    end = block.index(b"\r\n\r\n")
    lines = block[:end].decode("utf-8", "surrogatepass").split("\r\n")[1:]
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}, end + 4


def parse_record(raw: bytes) -> tuple[int | None, str, int, str, str, int | None, bytes]:
    """page_id, url, payload_bytes, payload_digest, record_type, refers_to, payload of one member."""
    if not raw.startswith(b"WARC/"):
        raise ValueError("not a WARC record")
    fields, at = headers_of(raw)
    size = int(fields["content-length"])
    block = raw[at : at + size]
    if len(block) != size or raw[at + size :] != b"\r\n\r\n":
        raise ValueError("a record's length does not match its frame")
    http, body_at = headers_of(block)
    payload, digest = block[body_at:], fields["warc-payload-digest"].removeprefix("sha256:")
    kind = fields["warc-type"]
    if kind == "response" and (hashlib.sha256(payload).hexdigest() != digest or len(payload) != int(http["content-length"])):
        raise ValueError("a payload does not match its digest")
    refers = from_urn(fields["warc-refers-to"]) if kind == "revisit" else None
    return from_urn(fields["warc-record-id"]), fields["warc-target-uri"], int(http["content-length"]), digest, kind, refers, payload


def write_archives(pages: DataFrame, least: int = 100, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Write pages as archives, one file per task, and return the table of files: path, records, bytes.

    Digests of the payloads are counted narrow; only digests that more than one page has are joined
    back, a join whose hot keys adaptive execution can split.
    """
    spark = pages.sparkSession
    folder = scratch_path(spark, "warc")
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.coalesce(F.col(html_col).cast("string"), F.lit("")).cast("binary").alias("payload"))
    rows = rows.withColumn("digest", F.sha2("payload", 256))
    same = rows.filter((F.length("payload") >= least) & F.col("page_id").isNotNull()).groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    same = materialize(same.select(F.col("digest").alias("same_digest"), "first_id"), "warc-same")
    # a row that cannot revisit gets a key of its own, so that it meets nothing and loads no single task
    key = F.when((F.length("payload") >= least) & F.col("page_id").isNotNull(), F.col("digest")).otherwise(F.concat(F.lit("-"), F.coalesce(F.col("page_id").cast("string"), F.col("url"), F.lit(""))))
    marked = rows.withColumn("key", key).join(same, F.col("key") == F.col("same_digest"), "left")
    marked = marked.withColumn("refers_to", F.when(F.col("first_id") < F.col("page_id"), F.col("first_id")))
    marked = marked.select("page_id", "url", F.when(F.col("refers_to").isNull(), F.col("payload")).alias("payload"), F.length("payload").alias("size"), "digest", "refers_to")
    schema = pa.schema([("path", pa.string()), ("records", pa.int64()), ("bytes", pa.int64())])

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, sink, records, size = TaskContext.get(), None, 0, 0
        fs, base = open_fs(folder)
        for page_id, url, payload, length, digest, refers_to in arrow_rows(batches, "page_id", "url", "payload", "size", "digest", "refers_to"):
            if sink is None:
                path = f"part-{task.partitionId():06d}-{task.taskAttemptId()}.warc.gz"
                fs.create_dir(base, recursive=True)
                sink = fs.open_output_stream(f"{base}/{path}", compression=None)
            member = gzip_member(record_bytes(page_id, url, bytes(length) if payload is None else payload, digest, refers_to))
            sink.write(member)
            records, size = records + 1, size + len(member)
        if sink is not None:
            sink.close()
            yield pa.RecordBatch.from_pydict({"path": [f"{folder}/{path}"], "records": [records], "bytes": [size]}, schema)

    return materialize(marked.mapInArrow(tidy(write), "path string, records long, bytes long"), "warc-files")


def read_archives(files: DataFrame, with_payload: bool = False) -> DataFrame:
    """Every record of the archives named in ``files``, one task per file at a time."""
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = RowBuffer(schema)
        for (path,) in arrow_rows(batches, "path"):
            fs, local = open_fs(path)
            with fs.open_input_stream(local, compression=None) as source:
                for raw in members(source):
                    *row, payload = parse_record(raw)
                    if out.add(*row, payload if with_payload else None, weight=len(payload) * with_payload):
                        yield out.take()
        if len(out):
            yield out.take()

    spread = files.select("path").repartition(max(1, int(files.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    found = spread.mapInArrow(tidy(read), "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary")
    return found if with_payload else found.drop("payload")


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    back = read_archives(write_archives(table(spark, sf_dir, "pages")))
    return back.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


QUERIES = {"op5_warc": op5_warc}
ORACLES = {
    "op5_warc": """
        WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
        d AS (SELECT page_id, octet_length(b) AS payload_bytes, sha256(b) AS payload_digest FROM p),
        f AS (SELECT *, CASE WHEN payload_bytes >= 100 THEN min(page_id) OVER (PARTITION BY payload_digest) ELSE page_id END AS first_id FROM d)
        SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes, payload_digest,
               CASE WHEN first_id < page_id THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN first_id < page_id THEN first_id END AS refers_to
        FROM f""",
}
