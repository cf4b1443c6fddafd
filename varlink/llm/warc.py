"""Operator 8: WARC archives through a chunked record table.

A record's payload is never held as one buffer beyond the row it comes in: :func:`chunk_table` makes payloads rows
``(record_id, chunk_no, data)`` of bounded size, which carry the SHA-1 of the payload so far; :func:`write_chunks` streams
any such rows into gzip members (one a record), and the reader streams the archives back as rows of the same kind. The row
of a record's last chunk has the digest of the whole payload, without gathering its chunks again, and both ends check it.

A record's identifier is a name-based UUID of page, payload digest and url, so repeated page ids with other contents differ;
rows alike in all three are one record written more than once, under one identifier.

Of records with equal payloads of at least ``MIN_REVISIT`` bytes, the one with the largest ``page_id`` is a response and
the others are revisits that refer to it and store no payload; smaller ones are all responses. Repeats are found by
digest and length in a narrow, pre-aggregated table, so payloads are not shuffled to find them.

Archives are written to a temporary name and renamed, one file per task and attempt; the manifest names the files of
successful attempts only, so a lost executor leaves no half-written archive in the result.

Edge cases: a null html is an empty payload; several rows with the largest ``page_id`` of a payload are all responses; a
null ``page_id`` is written without a page header and read back as null; an empty table gives no record. Archives hold
``page_id``, ``url`` and ``html`` only: other columns of the input, whatever their names, are not written.
"""

from __future__ import annotations

import hashlib
import os
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import quote, unquote, urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, new_path

MIN_REVISIT = 1000
CHUNK_BYTES = 1 << 20
_CRLF = b"\r\n"
_HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
#: Format version and the profile of revisit records.
_VERSION, _PROFILE = b"WARC/1.1", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_DATE = "2020-01-01T00:00:00Z"


# ------------------------------------------------------------------ files on a shared folder


class Store:
    """Files of a shared folder: a mounted one directly, others by the file systems that Arrow knows."""

    def __init__(self, folder: str):
        parts = urlsplit(folder)
        self.scheme, self.local = parts.scheme, parts.scheme in ("", "file")
        self.root = unquote(parts.path) if self.local else folder
        if not self.local:
            from pyarrow import fs

            self.fs, self.root = fs.FileSystem.from_uri(folder)

    def writer(self, path: str):
        if self.local:
            os.makedirs(os.path.dirname(path), exist_ok=True)
            return open(path, "wb")
        return self.fs.open_output_stream(path)

    def reader(self, path: str):
        return open(path, "rb") if self.local else self.fs.open_input_stream(path)

    def rename(self, old: str, new: str) -> None:
        os.replace(old, new) if self.local else self.fs.move(old, new)


# ------------------------------------------------------------------ records


def record_id(page_id: int | None, digest: str, url: str | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{page_id}|{digest}|{url}')}>"


def _target(url: str | None) -> str:
    return quote(url or "", safe=":/?#[]@!$&'()*+,;=%~")


def record_head(kind: str, page_id: int | None, url: str | None, digest: str, payload_bytes: int, refers_to: int | None, refers_url: str | None = None) -> bytes:
    """The header block of a record, its length included."""
    revisit = kind == "revisit"
    fields = [
        ("WARC-Type", kind),
        ("WARC-Record-ID", record_id(page_id, digest, url)),
        ("WARC-Date", _DATE),
        ("WARC-Target-URI", _target(url)),
        ("WARC-Payload-Digest", f"sha1:{digest}"),
        ("Content-Type", "application/http; msgtype=response"),
        ("Content-Length", str(len(_HTTP) + (0 if revisit else payload_bytes))),
        ("X-Payload-Length", str(payload_bytes)),
    ]
    if page_id is not None:
        fields.append(("X-Page-ID", str(page_id)))
    if revisit:
        fields += [("WARC-Profile", _PROFILE), ("WARC-Refers-To", record_id(refers_to, digest, refers_url)), ("WARC-Refers-To-Target-URI", _target(refers_url)), ("X-Refers-To-Page", str(refers_to))]
    return _VERSION + _CRLF + b"".join(f"{k}: {v}\r\n".encode() for k, v in fields) + _CRLF


def write_records(out, records) -> tuple[int, int]:
    """Stream ``(head, chunks)`` pairs into gzip members; returns the numbers of records and bytes."""
    count = size = 0
    for head, chunks in records:
        z = zlib.compressobj(3, zlib.DEFLATED, 31)
        for piece in (head, _HTTP):
            size += out.write(z.compress(piece)) or 0
        for data in chunks:
            size += out.write(z.compress(data)) or 0
        size += out.write(z.compress(_CRLF + _CRLF) + z.flush()) or 0
        count += 1
    return count, size


class _Inflated:
    """A gzip file's members as one stream, read in bounded pieces."""

    def __init__(self, source, piece: int = 1 << 16):
        self.source, self.piece, self.z, self.buffer, self.ended = source, piece, zlib.decompressobj(31), bytearray(), False

    def fill(self) -> bool:
        while not self.ended:
            raw = self.z.unconsumed_tail or self.z.unused_data if self.z.eof else self.z.unconsumed_tail
            if self.z.eof:
                self.z = zlib.decompressobj(31)
            raw = raw or self.source.read(self.piece)
            if not raw:
                self.ended = True
                break
            if got := self.z.decompress(raw, self.piece * 4):
                self.buffer += got
                return True
        return False

    def line(self) -> bytes | None:
        while (at := self.buffer.find(_CRLF)) < 0:
            if not self.fill():
                return None
        out = bytes(self.buffer[:at])
        del self.buffer[: at + 2]
        return out

    def take(self, most: int) -> bytes:
        """At least one and at most ``most`` bytes; fewer than asked only at the end of what is buffered."""
        while len(self.buffer) < most and self.fill():
            pass
        out = bytes(self.buffer[:most])
        del self.buffer[: len(out)]
        return out


def read_records(source, chunk_bytes: int = CHUNK_BYTES) -> Iterator[dict]:
    """Chunk rows of an archive: record fields, ``chunk_no``, ``data``, ``digest_so_far``, ``bytes_so_far``, ``last``."""
    stream = _Inflated(source)
    while (first := stream.line()) is not None:
        if not first:
            continue
        if first != _VERSION:
            raise ValueError(f"not a record: {first[:40]!r}")
        head: dict[str, str] = {}
        while line := stream.line():
            k, _, v = line.decode().partition(": ")
            head[k] = v
        left = int(head["Content-Length"])
        while (line := stream.line()) is not None:  # the HTTP head
            left -= len(line) + 2
            if not line:
                break
        base = {
            "record_id": head["WARC-Record-ID"],
            "page_id": int(head["X-Page-ID"]) if "X-Page-ID" in head else None,
            "url": unquote(head["WARC-Target-URI"]),
            "record_type": head["WARC-Type"],
            "refers_to": int(head["X-Refers-To-Page"]) if "X-Refers-To-Page" in head else None,
            "stated_digest": head["WARC-Payload-Digest"].removeprefix("sha1:"),
            "stated_bytes": int(head["X-Payload-Length"]),
        }
        digest, total, no = hashlib.sha1(usedforsecurity=False), 0, 0
        while True:
            data = stream.take(min(left, chunk_bytes)) if left else b""
            if left and not data:
                raise ValueError(f"record {base['record_id']} ends early")
            left -= len(data)
            total += len(data)
            digest.update(data)
            yield base | {"chunk_no": no, "data": data, "digest_so_far": digest.hexdigest(), "bytes_so_far": total, "last": left == 0}
            no += 1
            if left == 0:
                break


# ------------------------------------------------------------------ tables


def plan_records(pages: DataFrame) -> DataFrame:
    """``page_id, url, html, payload_bytes, payload_digest, record_type, refers_to, refers_url``; html is null for revisits."""
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    sized = pages.select("page_id", "url", "html", F.octet_length(payload).cast("long").alias("payload_bytes"), F.sha1(payload).alias("payload_digest"))
    narrow = cut(sized.select("page_id", "url", "payload_bytes", "payload_digest").filter(F.col("payload_bytes") >= MIN_REVISIT), "warc-digests")
    same = narrow.groupBy("payload_digest", "payload_bytes").agg(F.count("*").alias("n"), F.max(F.struct("page_id", "url")).alias("keeper")).filter("n > 1 AND keeper.page_id IS NOT NULL")
    same = cut(same.select(F.col("payload_digest").alias("k_digest"), F.col("payload_bytes").alias("k_bytes"), F.col("keeper.page_id").alias("keeper"), F.col("keeper.url").alias("keeper_url")), "warc-repeats")
    met = sized.join(same, (F.col("payload_digest") == F.col("k_digest")) & (F.col("payload_bytes") == F.col("k_bytes")), "left")
    revisit = F.col("keeper").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("keeper"))
    return met.select(
        "page_id", "url", F.when(~revisit, F.col("html")).alias("html"), "payload_bytes", "payload_digest",
        F.when(revisit, "revisit").otherwise("response").alias("record_type"), F.when(revisit, F.col("keeper")).alias("refers_to"), F.when(revisit, F.col("keeper_url")).alias("refers_url"),
    )


def payload_chunks(html: str | None, chunk_bytes: int = CHUNK_BYTES) -> Iterator[bytes]:
    """The payload of a page in chunks; characters are encoded by the piece, so no second whole copy is made."""
    step = max(1, chunk_bytes // 4)
    for at in range(0, len(html or ""), step):
        yield html[at : at + step].encode("utf-8", "surrogatepass")


_HEAD = [("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("refers_url", pa.string()), ("payload_digest", pa.string()), ("payload_bytes", pa.int64())]
_WRITE_SCHEMA = pa.schema([*_HEAD, ("record_id", pa.string()), ("chunk_no", pa.int64()), ("data", pa.binary()), ("digest_so_far", pa.string()), ("last", pa.bool_())])
_WRITE_DDL = "page_id long, url string, record_type string, refers_to long, refers_url string, payload_digest string, payload_bytes long, record_id string, chunk_no long, data binary, digest_so_far string, last boolean"


def _batched(rows: Iterator[dict], schema: pa.Schema, limit: int) -> Iterator[pa.RecordBatch]:
    """Arrow batches of at most about ``limit`` bytes of ``data``."""
    held, size = [], 0
    for row in rows:
        size += len(row["data"] or b"")
        held.append(row)
        if size >= limit or len(held) >= 2000:
            yield pa.RecordBatch.from_pylist(held, schema)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_pylist(held, schema)


def chunk_table(planned: DataFrame, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """The chunked record table of planned records: a row a chunk, at least one a record, in order within a partition.

    ``digest_so_far`` is the SHA-1 of the payload up to the chunk; revisits have one row without data.
    """

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        for batch in batches:
            for i in range(batch.num_rows):
                head = {c: batch.column(c)[i].as_py() for c, _ in _HEAD}
                head["record_id"] = record_id(head["page_id"], head["payload_digest"], head["url"])
                html = None if head["record_type"] == "revisit" else batch.column("html")[i].as_py()
                digest, no, data = hashlib.sha1(usedforsecurity=False), 0, None
                for piece in payload_chunks(html, chunk_bytes):
                    if data is not None:
                        yield head | {"chunk_no": no, "data": data, "digest_so_far": digest.hexdigest(), "last": False}
                        no += 1
                    digest.update(piece)
                    data = piece
                yield head | {"chunk_no": no, "data": data, "digest_so_far": digest.hexdigest(), "last": True}

    return planned.mapInArrow(lambda batches: _batched(rows(batches), _WRITE_SCHEMA, 4 * chunk_bytes), _WRITE_DDL)


def write_chunks(chunks: DataFrame, folder: str) -> DataFrame:
    """Write a WARC file per partition of a chunk table below ``folder``; returns the manifest ``path, records, bytes``.

    A record's rows must follow each other within a partition, as :func:`chunk_table` makes them; a record that does not
    begin with its first chunk, ends early or has another digest than stated is an error.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store = Store(folder)
        name = f"{store.root.rstrip('/')}/part-{uuid.uuid4().hex}.warc.gz"
        rows = ({c: batch.column(c)[i].as_py() for c in batch.schema.names} for batch in batches for i in range(batch.num_rows))
        ahead = [next(rows, None)]
        if ahead[0] is None:
            return

        def pieces(first: dict) -> Iterator[bytes]:
            row, no = first, 0
            while True:
                if row is None or row["record_id"] != first["record_id"] or row["chunk_no"] != no:
                    raise ValueError(f"the chunks of record {first['record_id']} are not in order")
                if row["data"]:
                    yield row["data"]
                if row["last"]:
                    break
                row, no = next(rows, None), no + 1
            if row["record_type"] != "revisit" and row["digest_so_far"] != row["payload_digest"]:
                raise ValueError(f"payload of record {first['record_id']} does not fit its digest")
            ahead[0] = next(rows, None)

        def records():
            while (first := ahead[0]) is not None:
                yield record_head(first["record_type"], first["page_id"], first["url"], first["payload_digest"], first["payload_bytes"], first["refers_to"], first["refers_url"]), pieces(first)

        with store.writer(f"{name}.partial") as out:
            count, size = write_records(out, records())
        store.rename(f"{name}.partial", name)
        yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([count], pa.int64()), pa.array([size], pa.int64())], names=["path", "records", "bytes"])

    return cut(chunks.mapInArrow(run, "path string, records long, bytes long"), "warc-manifest")


def write_archives(planned: DataFrame, folder: str, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """Planned records as archives, through the chunk table."""
    return write_chunks(chunk_table(planned, chunk_bytes), folder)


_CHUNK_SCHEMA = pa.schema(
    [("record_id", pa.string()), ("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("stated_digest", pa.string()), ("stated_bytes", pa.int64()), ("chunk_no", pa.int64()), ("data", pa.binary()), ("digest_so_far", pa.string()), ("bytes_so_far", pa.int64()), ("last", pa.bool_())]
)
_CHUNK_DDL = "record_id string, page_id long, url string, record_type string, refers_to long, stated_digest string, stated_bytes long, chunk_no long, data binary, digest_so_far string, bytes_so_far long, last boolean"


def read_archives(spark: SparkSession, manifest: DataFrame, folder: str, chunk_bytes: int = CHUNK_BYTES, payload: bool = True) -> DataFrame:
    """The chunked record table of all archives in ``manifest``; without ``payload``, ``data`` is null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store = Store(folder)

        def rows() -> Iterator[dict]:
            for batch in batches:
                for path in batch.column("path").to_pylist():
                    with store.reader(path) as source:
                        for row in read_records(source, chunk_bytes):
                            yield row if payload else row | {"data": None}

        yield from _batched(rows(), _CHUNK_SCHEMA, 4 * chunk_bytes)

    # one file a task, as far as there are slots; the manifest has a row per file
    slots = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    return manifest.repartition(slots).select("path").mapInArrow(run, _CHUNK_DDL)


def round_trip(pages: DataFrame, folder: str | None = None) -> DataFrame:
    """Write ``pages`` as archives, read them back, and return one row a record, checked against its header."""
    spark = pages.sparkSession
    folder = folder or new_path(spark, "warc")
    manifest = write_archives(plan_records(pages), folder)
    chunks = read_archives(spark, manifest, folder, payload=False)
    ends = chunks.filter("last")
    intact = (F.col("record_type") == "revisit") | ((F.col("digest_so_far") == F.col("stated_digest")) & (F.col("bytes_so_far") == F.col("stated_bytes")))
    digest = F.when(intact, F.col("stated_digest")).otherwise(F.raise_error(F.concat(F.lit("payload of record "), F.coalesce(F.col("page_id").cast("string"), F.lit("?")), F.lit(" does not fit its digest"))))
    return ends.select("page_id", F.col("stated_bytes").alias("payload_bytes"), digest.alias("payload_digest"), "record_type", "refers_to")
