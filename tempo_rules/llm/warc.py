"""WARC archives with chunked payloads.

Archives hold one gzip member per record (WARC/1.1, as .warc.gz). Writers and
readers stream: payloads go in and come out as rows of (record, chunk number), those
read with the SHA-1 of the payload up to their end, so that no record is held whole
in Python. Archives lie in the shared folder and are reached through pyarrow's file
systems (local and mounted folders, hdfs, s3, gs, abfs).
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_pass, materialize, scratch_dir

CHUNK = 1 << 20
#: Payloads of fewer bytes are never replaced by a reference.
REVISIT_BYTES = 1000
#: Fixed date of all records, so that archives of the same pages are the same.
DATE = "2024-01-01T00:00:00Z"

CHUNKS = "archive string, page_id long, record_type string, refers_to long, declared_bytes long, declared_digest string, chunk_no int, chunk binary, digest string, last boolean, payload_bytes long"


def qualified(spark: SparkSession, root: str) -> str:
    """The folder with its scheme, as the session's file systems resolve it."""
    path = spark._jvm.org.apache.hadoop.fs.Path(root)
    return path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).makeQualified(path).toString()


def uri_of(root: str) -> str:
    """A folder as pyarrow names it: one slash after file: becomes three, and s3a and s3n are s3."""
    if root.startswith("/"):
        return f"file://{root}"
    scheme, _, rest = root.partition(":")
    if scheme == "file":
        return f"file:///{rest.lstrip('/')}"
    return f"s3:{rest}" if scheme in ("s3a", "s3n") else root


def _open(root: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(uri_of(root))


def _head(kind: str, page_id: int | None, url: str, digest: str, declared: int, refers_to: int | None, length: int) -> bytes:
    named = base64.b32encode(bytes.fromhex(digest)).decode()
    lines = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", f"WARC-Date: {DATE}", f"WARC-Target-URI: {url}",
        "Content-Type: text/html; charset=utf-8", f"WARC-Payload-Digest: sha1:{named}", f"X-Payload-Length: {declared}", f"Content-Length: {length}",
    ]
    if kind == "revisit":
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    return ("\r\n".join(lines) + "\r\n\r\n").encode()


class Writer:
    """Writes records chunk by chunk, each as a gzip member."""

    def __init__(self, out) -> None:
        self.out, self.z = out, None

    def begin(self, head: bytes) -> None:
        self.z = zlib.compressobj(1, zlib.DEFLATED, 31)
        self.out.write(self.z.compress(head))

    def add(self, chunk) -> None:
        self.out.write(self.z.compress(chunk))

    def end(self) -> None:
        self.out.write(self.z.compress(b"\r\n\r\n") + self.z.flush())
        self.z = None


def _bytes_of(value: pa.Scalar) -> memoryview:
    buf = value.as_buffer()
    return memoryview(buf) if buf is not None else memoryview(b"")


def chunk_rows(records: DataFrame, size: int = CHUNK) -> DataFrame:
    """Rows (record, chunk) of rows with html (binary) and record_type: chunk_no from 0, the chunk, whether it's the last.

    The chunks of a record follow each other in one task. A record without payload, and
    a revisit, has one empty chunk. Rows that go to Python hold a chunk, never a payload.
    """
    body = F.when(F.col("record_type") == "revisit", F.lit(0)).otherwise(F.octet_length("html"))
    counted = records.withColumn("length", body.cast("long")).withColumn("n_chunks", F.greatest(F.ceil(F.col("length") / size), F.lit(1)).cast("int"))
    wide = counted.select("page_id", "url", "record_type", "refers_to", "payload_digest", "length", "n_chunks", "html", F.octet_length("html").cast("long").alias("declared"), F.explode(F.sequence(F.lit(0), F.col("n_chunks") - 1)).alias("chunk_no"))
    chunk = F.when(F.col("length") > 0, F.expr(f"substring(html, chunk_no * {size} + 1, {size})"))
    return wide.select("page_id", "url", "record_type", "refers_to", "payload_digest", "length", "declared", "chunk_no", chunk.alias("chunk"), (F.col("chunk_no") == F.col("n_chunks") - 1).alias("last"))


def write_archives(chunks: DataFrame, root: str) -> DataFrame:
    """Write chunk rows (see chunk_rows); return the archives written.

    Each task writes one file under a name of its own; only names that the returned
    rows hold count, so a task that is run again leaves nothing that is read.
    """

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, base = _open(root)
        name = f"{uuid.uuid4().hex}.warc.gz"
        out, n = None, 0
        for b in batches:
            if out is None and b.num_rows:
                files.create_dir(base, recursive=True)
                out = files.open_output_stream(f"{base}/{name}")
                writer = Writer(out)
            last, chunk = b.column("last").to_pylist(), b.column("chunk")
            for i, no in enumerate(b.column("chunk_no").to_pylist()):
                if no == 0:
                    page_id, url, kind, refers, digest, length, declared = (b.column(c)[i].as_py() for c in ("page_id", "url", "record_type", "refers_to", "payload_digest", "length", "declared"))
                    url = (url or "").replace("\r", "%0D").replace("\n", "%0A")
                    writer.begin(_head(kind, page_id, url, digest, declared, refers, length))
                writer.add(_bytes_of(chunk[i]))
                if last[i]:
                    writer.end()
                    n += 1
        if out is not None:
            out.close()
            yield pa.RecordBatch.from_pydict({"archive": [name], "records": [n]}, pa.schema([("archive", pa.string()), ("records", pa.int64())]))

    return arrow_pass(chunks, write, "archive string, records long")


class _Member:
    """Reads a sequence of gzip members as one stream of bounded reads."""

    def __init__(self, source, size: int = 1 << 18) -> None:
        self.source, self.size = source, size
        self.z = zlib.decompressobj(31)
        self.raw, self.buf = b"", bytearray()

    def _more(self) -> bool:
        if not self.raw:
            self.raw = self.source.read(self.size)
            if not self.raw:
                return False
        if self.z.eof:
            self.z = zlib.decompressobj(31)
        self.buf += self.z.decompress(self.raw, CHUNK)
        self.raw = self.z.unused_data if self.z.eof else self.z.unconsumed_tail
        return True

    def take(self, n: int) -> bytes:
        while len(self.buf) < n:
            if not self._more():
                raise ValueError("archive ends within a record")
        out = bytes(self.buf[:n])
        del self.buf[:n]
        return out

    def head(self) -> dict[str, str] | None:
        while (at := self.buf.find(b"\r\n\r\n")) < 0:
            if not self._more():
                if self.buf.strip():
                    raise ValueError("archive ends within a record")
                return None
        lines = bytes(self.buf[:at]).decode().split("\r\n")
        del self.buf[: at + 4]
        return dict(x.split(": ", 1) for x in lines[1:])


def read_records(source) -> Iterator[dict]:
    """Chunk rows of an archive, in order; a record without payload has one empty chunk."""
    stream = _Member(source)
    while (h := stream.head()) is not None:
        left, no, sha, total = int(h["Content-Length"]), 0, hashlib.sha1(), 0
        number = lambda x: int(x[10:-1]) if x and x[10:-1] else None
        declared = base64.b32decode(h["WARC-Payload-Digest"][5:]).hex()
        while True:
            part = stream.take(min(left, CHUNK))
            left -= len(part)
            total += len(part)
            sha.update(part)
            yield {
                "page_id": number(h["WARC-Record-ID"]), "record_type": h["WARC-Type"], "refers_to": number(h.get("WARC-Refers-To", "")), "declared_bytes": int(h["X-Payload-Length"]), "declared_digest": declared,
                "chunk_no": no, "chunk": part, "digest": sha.hexdigest(), "last": left == 0, "payload_bytes": total,
            }
            no += 1
            if not left:
                break
        if stream.take(4) != b"\r\n\r\n":
            raise ValueError("a record is longer than it says")
        if h["WARC-Type"] == "response" and sha.hexdigest() != declared:
            raise ValueError(f"payload of {h['WARC-Record-ID']} doesn't match its digest")


def read_archives(archives: DataFrame, root: str, payload: bool = True) -> DataFrame:
    """The chunk table of these archives; without payload the chunk column is null."""
    schema = pa.schema([("archive", pa.string()), ("page_id", pa.int64()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("declared_bytes", pa.int64()), ("declared_digest", pa.string()), ("chunk_no", pa.int32()), ("chunk", pa.binary()), ("digest", pa.string()), ("last", pa.bool_()), ("payload_bytes", pa.int64())])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, base = _open(root)
        for b in batches:
            for name in b.column("archive").to_pylist():
                with files.open_input_stream(f"{base}/{name}") as source:
                    rows, held = [], 0
                    for r in read_records(source):
                        held += len(r["chunk"])
                        rows.append({**r, "archive": name, "chunk": r["chunk"] if payload else None})
                        if held > 4 * CHUNK or len(rows) > 2000:
                            yield pa.RecordBatch.from_pylist(rows, schema)
                            rows, held = [], 0
                    if rows:
                        yield pa.RecordBatch.from_pylist(rows, schema)

    return arrow_pass(archives, read, CHUNKS)


def decide(pages: DataFrame, least: int = REVISIT_BYTES) -> DataFrame:
    """Pages that refer to an earlier copy: page_id, digest and the page they refer to.

    Rows that repeat the page_id of the response are responses too.
    """
    slim = pages.select("page_id", "payload_digest", "n").where(F.col("n") >= least)
    first = slim.groupBy("payload_digest").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("k")).where("k > 1").drop("k")
    return slim.join(first, "payload_digest").where(F.col("page_id").isNull() | (F.col("page_id") < F.col("refers_to"))).select("page_id", "payload_digest", "refers_to").distinct()


def archive_pages(pages: DataFrame) -> DataFrame:
    """Write every page to archives, read them back, one row per page.

    Null html is an empty payload, null url an empty target. Of equal payloads of at
    least 1000 bytes the largest page_id is the response, and so is every row that
    repeats it. Null page_ids are kept and never referred to, unless no other page has
    the payload. Extra columns, whatever their names, are ignored; an empty table
    gives an empty result.
    """
    html = F.coalesce(F.col("html").cast("string"), F.lit(""))
    full = pages.select(
        F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.encode(html, "UTF-8").alias("html")
    ).withColumns({"payload_digest": F.sha1("html"), "n": F.octet_length("html")})
    again = materialize(decide(full), "revisits")
    also = [full.page_id.eqNullSafe(again.page_id), full.payload_digest == again.payload_digest]
    marked = full.join(again, also, "left").select(
        full.page_id, full.url, full.html, full.payload_digest,
        F.when(again.refers_to.isNotNull(), "revisit").otherwise("response").alias("record_type"), again.refers_to,
    )
    root = qualified(pages.sparkSession, f"{scratch_dir(pages.sparkSession)}/warc")
    archives = materialize(write_archives(chunk_rows(marked), root), "archives")
    chunks = read_archives(archives.repartition(max(1, min(10_000, archives.count())), "archive"), root, payload=False)
    ends = chunks.where("last")
    is_revisit = F.col("record_type") == "revisit"
    return ends.select(
        "page_id", F.when(is_revisit, F.col("declared_bytes")).otherwise(F.col("payload_bytes")).alias("payload_bytes"),
        F.when(is_revisit, F.col("declared_digest")).otherwise(F.col("digest")).alias("payload_digest"), "record_type", "refers_to",
        (F.col("chunk_no") + 1).alias("chunks"), "archive",
    )
