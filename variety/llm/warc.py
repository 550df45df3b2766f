"""WARC archives: writing with segments and revisits, reading with reassembly.

Archives are written by Spark's text writer, a record a line whose end is the record's own
last byte, so they appear on any file system that Spark knows and under its commit protocol.
They are read as binary files. Continuation records are grouped by their origin, put in order of
their segment numbers, checked against the total length, and their chunked transfer framing is decoded.
"""

from __future__ import annotations

import gzip
import io
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import scratch_path, table, written

#: Payloads below this many bytes are written in full, however often they repeat.
REVISIT_BYTES = 100
SEGMENT_BYTES = 16 << 10
CHUNK_BYTES = 8 << 10
BATCH_BYTES = 4 << 20
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP_HEAD = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n"


def record_id(page_id: int | None, digest: str) -> str:
    """A URN made of the payload's digest and the page; pages of none have an X in their place."""
    return f"urn:page:{digest[:16]}:{'X' if page_id is None else page_id}"


def page_of(urn: str) -> int | None:
    page = urn.rsplit(":", 1)[1]
    return None if page == "X" else int(page)


def chunked(payload: bytes, size: int = CHUNK_BYTES) -> bytes:
    parts = []
    for at in range(0, len(payload), size):
        part = payload[at : at + size]
        parts += [b"%x\r\n" % len(part), part, b"\r\n"]
    return b"".join([*parts, b"0\r\n\r\n"])


def dechunked(body: bytes) -> bytes | None:
    """The payload in chunked framing; None if the framing is broken."""
    parts, at = [], 0
    while True:
        end = body.find(b"\r\n", at)
        try:
            size = int(body[at:end].split(b";")[0], 16) if end > at else -1
        except ValueError:
            return None
        if size < 0 or end + 2 + size > len(body):
            return None
        if not size:
            return b"".join(parts)
        parts.append(body[end + 2 : end + 2 + size])
        at = end + 2 + size
        if body[at : at + 2] != b"\r\n":
            return None
        at += 2


def payload_of(block: bytes) -> bytes | None:
    """The payload of an HTTP response block."""
    head, sep, body = block.partition(b"\r\n\r\n")
    if not sep:
        return None
    return dechunked(body) if b"transfer-encoding: chunked" in head.lower() else body


def record(fields: list[tuple[str, object]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in fields if v is not None)
    return b"WARC/1.1\r\n" + head.encode() + b"Content-Length: %d\r\n\r\n" % len(block) + block + b"\r\n\r\n"


def page_records(page_id: int | None, uri: str | None, payload: bytes, digest: str, refers_to: int | None, segment: int = SEGMENT_BYTES) -> Iterator[bytes]:
    """The records of one page: a revisit, a response, or a response with its continuations."""
    me = record_id(page_id, digest)
    uri = "".join(c for c in uri or "" if c >= " ") or None
    common = [("WARC-Target-URI", uri), ("WARC-Payload-Digest", f"sha256:{digest}"), ("Content-Type", "application/http;msgtype=response")]
    if refers_to is not None:
        yield record([("WARC-Type", "revisit"), ("WARC-Record-ID", f"<{me}>"), ("WARC-Refers-To", f"<{record_id(refers_to, digest)}>"), ("WARC-Profile", PROFILE), *common], HTTP_HEAD)
        return
    block = HTTP_HEAD + chunked(payload)
    parts = [block[i : i + segment] for i in range(0, len(block), segment)]
    yield record([("WARC-Type", "response"), ("WARC-Record-ID", f"<{me}>"), ("WARC-Segment-Number", 1 if len(parts) > 1 else None), *common], parts[0])
    for n, part in enumerate(parts[1:], 2):
        yield record(
            [
                ("WARC-Type", "continuation"),
                ("WARC-Record-ID", f"<{me}:{n}>"),
                ("WARC-Segment-Origin-ID", f"<{me}>"),
                ("WARC-Segment-Number", n),
                ("WARC-Segment-Total-Length", len(block) if n == len(parts) else None),
                ("WARC-Target-URI", uri),
            ],
            part,
        )


def _write(segment: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                rows = whole.slice(at, 256)
                out = []
                for page, uri, payload, digest, refers in zip(*(c.to_pylist() for c in rows.columns), strict=True):
                    out += [r[:-1] for r in page_records(page, uri, payload, digest, refers, segment)]
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["record"])

    return run


def write_archives(pages: DataFrame, path: str, segment: int = SEGMENT_BYTES) -> None:
    """Write a record for each row of ``pages`` (page_id, url, html) to gzipped archives under ``path``.

    Of rows with equal payloads of at least ``REVISIT_BYTES`` that with the smallest page_id is a
    response and the others revisit it. A null html is an empty payload. Rows that repeat both page_id and payload
    are written alike. A null page_id never stands for others. An empty table gives archives without records.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce(F.encode("html", "UTF-8"), F.lit(b"")).alias("payload"))
    rows = rows.withColumn("digest", F.sha2("payload", 256))
    big = F.octet_length("payload") >= REVISIT_BYTES
    first = rows.where(big).groupBy("digest").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1 and first is not null").drop("n")
    refers = F.when(~F.col("first").eqNullSafe(F.col("page_id")), F.col("first"))
    told = rows.join(first, "digest", "left").select("page_id", "url", "payload", "digest", refers.alias("refers_to"))
    lines = told.mapInArrow(_write(segment), "record binary").select(F.col("record").cast("string"))
    lines.write.option("lineSep", "\n").option("compression", "gzip").text(path)


def records(stream) -> Iterator[tuple[dict[str, str], bytes]]:
    """Fields (lower-case names) and block of each record of an uncompressed archive."""
    while line := stream.readline():
        if not line.strip():
            continue
        if not line.startswith(b"WARC/"):
            raise ValueError(f"not a WARC record: {line[:40]!r}")
        fields = {}
        while (line := stream.readline()).strip():
            name, _, value = line.decode().partition(":")
            fields[name.strip().lower()] = value.strip()
        size = int(fields["content-length"])
        block = stream.read(size)
        if len(block) != size:
            raise ValueError("the archive ends within a record")
        yield fields, block


PARSED = "record_id string, type string, uri string, refers_to string, segment int, total long, block binary"


def _parse(parts: bool):
    """Records that are whole (their payload in place of the block), or only those in segments (the block as it is)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema(
            [("record_id", pa.string()), ("type", pa.string()), ("uri", pa.string()), ("refers_to", pa.string()), ("segment", pa.int32()), ("total", pa.int64()), ("block", pa.binary())]
        )
        rows, held = [], 0

        def flush():
            out = pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)
            rows.clear()
            return out

        for batch in batches:
            for content in batch.column("content"):
                raw = io.BytesIO(content.as_py())
                stream = io.BufferedReader(gzip.GzipFile(fileobj=raw), 1 << 16) if raw.getbuffer()[:2] == b"\x1f\x8b" else raw
                for f, block in records(stream):
                    number = f.get("warc-segment-number")
                    if f["warc-type"] == "warcinfo" or (number is not None) != parts:
                        continue
                    strip = lambda k: f[k].strip("<>") if k in f else None  # noqa: B023, E731
                    if not parts:
                        block = payload_of(block) if f["warc-type"] == "response" else None
                    total = f.get("warc-segment-total-length")
                    rows.append((strip("warc-segment-origin-id") or strip("warc-record-id"), f["warc-type"], f.get("warc-target-uri"), strip("warc-refers-to"), number and int(number), total and int(total), block))
                    held += len(block or b"")
                    if held > BATCH_BYTES or len(rows) >= 4096:
                        yield flush()
                        held = 0
        if rows:
            yield flush()

    return run


def _assemble(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for at in range(0, whole.num_rows, 16):
            rows = whole.slice(at, 16)
            out = ([], [], [])
            for origin, uri, parts in zip(*(c.to_pylist() for c in rows.columns), strict=True):
                copies = Counter(p["segment"] for p in parts)
                by = {p["segment"]: p for p in parts}
                total = next((p["total"] for p in parts if p["total"] is not None), None)
                block = b"".join(by[n]["block"] for n in sorted(by))
                good = sorted(by) == [*range(1, len(by) + 1)] and total == len(block)
                for _ in range(copies.get(1, 1)):
                    for column, value in zip(out, (origin, uri, payload_of(block) if good else None), strict=True):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.string()), pa.array(out[1], pa.string()), pa.array(out[2], pa.binary())], ["record_id", "uri", "payload"])


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """record_id, type, uri, refers_to, payload of the responses and revisits in the archives under ``path``.

    Revisits have no payload of their own. A response whose segments are not complete, or whose
    length or framing doesn't agree, has a null payload. Segments may be in any archive.
    """
    files = spark.read.format("binaryFile").load(path).select("content")
    whole = files.mapInArrow(_parse(False), PARSED).select("record_id", "type", "uri", "refers_to", F.col("block").alias("payload"))
    parts = files.mapInArrow(_parse(True), PARSED)
    grouped = parts.groupBy("record_id").agg(F.max("uri").alias("uri"), F.collect_list(F.struct("segment", "total", "block")).alias("parts"))
    joined = grouped.mapInArrow(_assemble, "record_id string, uri string, payload binary")
    return whole.unionByName(joined.select("record_id", F.lit("response").alias("type"), "uri", F.lit(None).cast("string").alias("refers_to"), "payload"))


def resolved(found: DataFrame) -> DataFrame:
    """record_id, type, refers_to, payload_bytes, payload_digest; a revisit has those of the response that it refers to."""
    facts = found.select("record_id", "type", "refers_to", F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha2("payload", 256).alias("payload_digest"))
    facts = written(facts, "records")
    answers = facts.where("type = 'response'").groupBy(F.col("record_id").alias("refers_to")).agg(F.max("payload_bytes").alias("payload_bytes"), F.max("payload_digest").alias("payload_digest"))
    again = facts.where("type = 'revisit'").select("record_id", "type", "refers_to").join(answers, "refers_to", "left")
    return facts.where("type = 'response'").unionByName(again)


def op5_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch_path(spark, "archives")
    write_archives(table(spark, sf_dir, "pages"), path)
    page = lambda c: F.expr(f"try_cast(substring_index({c}, ':', -1) as bigint)")
    return resolved(read_archives(spark, path)).select(
        page("record_id").alias("page_id"), "payload_bytes", "payload_digest", F.col("type").alias("record_type"), page("refers_to").alias("refers_to")
    )
