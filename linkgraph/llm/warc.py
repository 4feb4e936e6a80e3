"""Web archive records as a chunked record table.

A record's bytes are rows of (record, chunk number, bytes); a payload beyond
``chunk_bytes`` never is one value again after it was cut.  Every chunk carries
the digest of the payload up to its end.  Rows in order form a valid archive
stream (WARC 1.1), and reading parses that stream: records of one chunk where
they lie, larger ones after their chunks were brought together and in order,
one chunk in memory at a time.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.llm.common import materialise

CHUNK_BYTES = 1 << 20
#: Payloads below this many bytes are always written in full.
REVISIT_LEAST = 100
_EPOCH = "1970-01-01T00:00:00Z"
_CHUNK_SCHEMA = "record string, page_id long, chunk long, last boolean, bytes binary, running_sha256 string"


def _clean(value: str | None) -> str:
    """A header value without controls or spaces."""
    return re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", value or "")


def record_head(record: str, url: str | None, kind: str, digest: str, size: int, refers_to: int | None) -> bytes:
    """Everything of a record before its payload; a revisit has no payload."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
    lines = [
        "WARC/1.1",
        f"WARC-Type: {kind}",
        f"WARC-Record-ID: <urn:page:{record}>",
        f"WARC-Target-URI: {_clean(url)}",
        f"WARC-Date: {_EPOCH}",
        f"WARC-Payload-Digest: sha256:{digest}",
        "Content-Type: application/http;msgtype=response",
    ]
    if kind == "revisit":
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    body = len(http) + (0 if kind == "revisit" else size)
    return ("\r\n".join(lines) + f"\r\nContent-Length: {body}\r\n\r\n").encode() + http


def _chunk_rows(chunk_bytes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["record", "page_id", "chunk", "last", "bytes", "running_sha256"]
        kinds = [pa.string(), pa.int64(), pa.int64(), pa.bool_(), pa.binary(), pa.string()]
        out: list[list] = [[] for _ in names]
        held = 0

        def emit() -> pa.RecordBatch:
            made = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], names=names)
            for c in out:
                c.clear()
            return made

        for batch in batches:
            columns = [batch.column(c) for c in ("record", "page_id", "url", "kind", "digest", "size", "refers_to", "html")]
            for k in range(batch.num_rows):
                record, page, url, kind, digest, size, refers = (c[k].as_py() for c in columns[:7])
                raw = columns[7][k].as_buffer() if columns[7][k].is_valid else None
                payload = memoryview(raw if raw is not None else b"") if kind == "response" else memoryview(b"")
                running = hashlib.sha256()
                count = max(1, -(-len(payload) // chunk_bytes))
                for c in range(count):
                    part = payload[c * chunk_bytes : (c + 1) * chunk_bytes]
                    running.update(part)
                    raw_chunk = bytes(part)
                    if c == 0:
                        raw_chunk = record_head(record, url, kind, digest, size, refers) + raw_chunk
                    if c == count - 1:
                        raw_chunk += b"\r\n\r\n"
                    for have, value in zip(out, (record, page, c, c == count - 1, raw_chunk, running.copy().hexdigest()), strict=True):
                        have.append(value)
                    held += len(raw_chunk)
                    if held > 4 << 20:
                        yield emit()
                        held = 0
        yield emit()

    return run


def plan_records(pages: DataFrame) -> DataFrame:
    """Pages with digest, size, record type and what they refer to.

    Of records with equal payloads of at least ``REVISIT_LEAST`` bytes, those
    with the smallest page_id are responses (more than one only if that
    page_id is repeated) and the others revisits of it.
    """
    html = F.coalesce("html", F.lit(""))
    base = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", html.alias("html")).withColumns({"digest": F.sha2("html", 256), "size": F.octet_length("html").cast("long")})
    groups = (
        base.filter((F.col("size") >= REVISIT_LEAST) & F.col("page_id").isNotNull())
        .groupBy("digest")
        .agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("n"))
        .filter("n > 1")
        .select("digest", "first")
    )
    out = base.join(groups, "digest", "left")
    again = (F.col("first") != F.col("page_id")) & (F.col("size") >= REVISIT_LEAST)
    return out.select(
        F.coalesce(F.col("page_id").cast("string"), F.lit("none")).alias("record"),
        "page_id",
        "url",
        F.when(again, F.lit("revisit")).otherwise(F.lit("response")).alias("kind"),
        "digest",
        "size",
        F.when(again, F.col("first")).alias("refers_to"),
        "html",
    )


def write_archive(pages: DataFrame, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """Archive chunks of all pages, as a table in the shared folder."""
    rows = plan_records(pages).withColumn("record", F.concat("record", F.lit("."), F.monotonically_increasing_id().cast("string")))
    return materialise(rows.mapInArrow(_chunk_rows(chunk_bytes), _CHUNK_SCHEMA), "archive")


_HEAD_END = b"\r\n\r\n"


def parse_records(chunks: Iterable[tuple[str, int | None, bytes, str]]) -> Iterator[tuple]:
    """Records of a chunk stream: (page_id, payload bytes, digest, type, refers_to).

    Only the head of a record is held; the payload is digested chunk by chunk
    and checked against the record's own digest and each chunk's running one.
    """
    left = 0
    state: dict = {}
    for _, page, raw, running in chunks:
        at = 0
        if not left:
            end = raw.index(_HEAD_END)
            fields = dict(line.split(": ", 1) for line in raw[:end].decode().split("\r\n")[1:])
            http_end = raw.index(_HEAD_END, end + 4)
            http = dict(line.split(": ", 1) for line in raw[end + 4 : http_end].decode().split("\r\n")[1:])
            at = http_end + 4
            left = int(fields["Content-Length"]) - (at - end - 4) + 4
            refers = fields.get("WARC-Refers-To")
            state = {"page": page, "kind": fields["WARC-Type"], "digest": fields["WARC-Payload-Digest"].removeprefix("sha256:"), "size": int(http["Content-Length"]), "got": 0, "sha": hashlib.sha256(), "refers": int(refers[len("<urn:page:") : -1]) if refers else None}
        body = memoryview(raw)[at:]
        if len(body) > left:
            raise ValueError(f"record of page {state['page']} is longer than its head says")
        payload = body[: max(0, len(body) - max(0, 4 - (left - len(body))))]
        state["sha"].update(payload)
        state["got"] += len(payload)
        left -= len(body)
        if state["kind"] == "response" and state["sha"].hexdigest() != running:
            raise ValueError(f"a chunk of page {state['page']} is damaged")
        if not left:
            if state["kind"] == "response" and (state["got"] != state["size"] or state["sha"].hexdigest() != state["digest"]):
                raise ValueError(f"payload of page {state['page']} is damaged")
            yield state["page"], state["size"], state["digest"], state["kind"], state["refers"]
    if left:
        raise ValueError("the archive ends within a record")


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]

    def rows() -> Iterator[tuple]:
        for batch in batches:
            columns = [batch.column(c) for c in ("record", "page_id", "bytes", "running_sha256")]
            for k in range(batch.num_rows):
                yield tuple(c[k].as_py() for c in columns)

    out: list[tuple] = []
    for record in parse_records(rows()):
        out.append(record)
        if len(out) >= 2000:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)
            out = []
    if out:
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)


_READ_SCHEMA = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"


def read_archive(chunks: DataFrame) -> DataFrame:
    """Parses archive chunks back to one row per record."""
    columns = ["record", "page_id", "chunk", "bytes", "running_sha256"]
    single = chunks.filter("chunk = 0 and last").select(columns).mapInArrow(_read, _READ_SCHEMA)
    many = chunks.filter("not (chunk = 0 and last)").select(columns).repartition("record").sortWithinPartitions("record", "chunk").mapInArrow(_read, _READ_SCHEMA)
    return single.union(many)


def archive_stream(chunks: DataFrame) -> Iterator[bytes]:
    """The bytes of an archive, for export to one file; chunks arrive one by one."""
    for row in chunks.orderBy("record", "chunk").select("bytes").toLocalIterator():
        yield bytes(row[0])


def round_trip(pages: DataFrame, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """Writes a record per row of ``pages`` and reads the archive back.

    A null html counts as empty; null or odd URLs are written escaped; rows that
    repeat a page_id give a record each; pages with a null page_id are responses
    of their own.  Other columns are ignored.
    """
    return read_archive(write_archive(pages, chunk_bytes))


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Archive round trip of the whole of ``pages``."""
    return round_trip(spark.read.parquet(f"{sf_dir}/pages.parquet"))


OP6_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
     d AS (SELECT page_id, strlen(html)::BIGINT AS payload_bytes, sha256(html) AS payload_digest FROM p),
     f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest, payload_bytes) AS first_id FROM d)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN first_id END AS refers_to
FROM f
"""
