"""WARC archives: write segmented, chunk-framed records; read, reassemble and verify them.

Writing: one record per row, as text lines whose separator is the record's own closing CRLF, so the
files are plain WARC/1.1 streams (gzip by file) made by Spark's writer on any store it reaches.
Equal payloads of at least ``revisit_bytes`` become revisit records that point at the row with the
largest key. Payloads are framed with chunked transfer coding; blocks above ``segment_bytes`` are
split into a first segment and continuation records.

Reading: whole files, parsed by Content-Length; records in one segment are decoded where they are,
segments are grouped by their origin record, ordered by number, checked against the total length,
joined and decoded. A group is one record's payload, so it is bounded by that record.

Edge cases: null or empty payloads give records of 0 bytes; invalid UTF-8 in a payload survives
(bytes are never decoded); a missing segment, wrong total length or broken chunk framing gives
``ok = false`` with the payload left null; an empty table writes no record and reads as no rows;
repeated and null keys are kept as separate records: their ids get a suffix that is the record's own
(partition and number), which reading takes off the key again. A revisit of such a row names its key.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
from collections.abc import Iterator

import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import join_small, materialise, work_path

CRLF = b"\r\n"
URN = "urn:row:"


def chunked(payload: bytes, size: int = 4096) -> bytes:
    """Chunked transfer framing of a payload."""
    parts = []
    for a in range(0, len(payload), size):
        piece = payload[a : a + size]
        parts += [b"%x" % len(piece), CRLF, piece, CRLF]
    return b"".join([*parts, b"0", CRLF, CRLF])


def dechunked(data: bytes) -> bytes | None:
    """The payload of chunked framing (extensions and trailers are skipped); None if it is broken."""
    parts, at = [], 0
    while True:
        end = data.find(CRLF, at)
        if end < 0:
            return None
        try:
            n = int(data[at:end].split(b";")[0].strip(), 16)
        except ValueError:
            return None
        at = end + 2
        if n == 0:
            return b"".join(parts) if data.find(CRLF, at) >= 0 else None
        if n < 0 or data[at + n : at + n + 2] != CRLF:
            return None
        parts.append(data[at : at + n])
        at += n + 2


def _record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    lines = "".join(f"{k}: {v}\r\n" for k, v in [*headers, ("Content-Length", str(len(block)))])
    return b"WARC/1.1\r\n" + lines.encode() + CRLF + block + CRLF  # the writer's separator adds the last CRLF


def _clean(x: object) -> str:
    return "".join(c for c in str(x or "") if c > "\x1f")


def records(key, uri, payload: bytes, digest: str, refers_to, segment_bytes: int, suffix: str = "") -> list[bytes]:
    """The records of one row: a response (with its continuations) or a revisit; ``suffix`` tells rows of one key apart."""
    own = f"{'' if key is None else key}{suffix}"
    sha1 = "sha1:" + base64.b32encode(bytes.fromhex(digest)).decode()
    head = [("WARC-Record-ID", f"<{URN}{own}>"), ("WARC-Target-URI", _clean(uri)), ("WARC-Date", "2024-01-01T00:00:00Z"), ("WARC-Payload-Digest", sha1), ("Content-Type", "application/http;msgtype=response")]
    if refers_to is not None:
        block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
        profile = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
        return [_record([("WARC-Type", "revisit"), *head, ("WARC-Refers-To", f"<{URN}{refers_to}>"), ("WARC-Profile", profile)], block)]
    block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n" + chunked(payload)
    if len(block) <= segment_bytes:
        return [_record([("WARC-Type", "response"), *head], block)]
    out = []
    cuts = range(0, len(block), segment_bytes)
    for n, a in enumerate(cuts, 1):
        part = block[a : a + segment_bytes]
        if n == 1:
            headers = [("WARC-Type", "response"), *head, ("WARC-Segment-Number", "1")]
        else:
            headers = [("WARC-Type", "continuation"), ("WARC-Record-ID", f"<{URN}{own}/{n}>"), head[2], ("WARC-Segment-Origin-ID", f"<{URN}{own}>"), ("WARC-Segment-Number", str(n))]
            if n == len(cuts):
                headers.append(("WARC-Segment-Total-Length", str(len(block))))
        out.append(_record(headers, part))
    return out


def write_archives(rows: DataFrame, path: str, segment_bytes: int = 16384, revisit_bytes: int = 1000, records_per_file: int = 2000, max_broadcast: int = 1_000_000) -> None:
    """``rows`` (key long, uri, payload binary) to WARC files below ``path``."""
    payload = F.coalesce(F.col("payload"), F.lit(b""))
    d = rows.select("key", "uri", payload.alias("payload")).withColumn("digest", F.sha1("payload")).withColumn("n", F.length("payload"))
    groups = d.where(F.col("n") >= revisit_bytes).groupBy("digest", "n").agg(F.max("key").alias("response"), F.count("*").alias("copies")).where("copies > 1").drop("copies")
    d = join_small(d, materialise(groups, "warc_groups"), ["digest", "n"], "left", max_broadcast)
    repeated = rows.where("key is not null").groupBy("key").count().where("count > 1").select("key", F.lit(True).alias("repeated"))
    d = join_small(d, materialise(repeated, "warc_repeated"), "key", "left", max_broadcast)
    shared = F.col("key").isNull() | F.coalesce("repeated", F.lit(False))
    d = d.select("key", "uri", "payload", "digest", F.when(F.col("response") != F.col("key"), F.col("response")).alias("refers_to"), shared.alias("shared"))

    def write(batches: Iterator) -> Iterator:
        import pyarrow as pa

        part, at = TaskContext.get().partitionId(), 0
        for b in batches:
            out = []
            for n, (*row, shared) in enumerate(zip(*[b.column(i).to_pylist() for i in range(6)]), at):
                out += records(*row, segment_bytes, f"/{part}.{n}" if shared else "")
            at += b.num_rows
            yield pa.RecordBatch.from_pydict({"record": pa.array(out, pa.binary())})

    made = d.mapInArrow(write, "record binary").select(F.col("record").cast("string").alias("value"))
    made.write.option("lineSep", "\r\n").option("compression", "gzip").option("maxRecordsPerFile", records_per_file).text(path)


def parse_stream(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers in lower case, block) of every record of an uncompressed stream; raises on broken framing."""
    at, total = 0, len(data)
    while at < total:
        if data[at : at + 2] == CRLF:  # the end of the record before, or padding
            at += 2
            continue
        if data[at : at + 5] != b"WARC/":
            raise ValueError(f"no record at byte {at}")
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            raise ValueError(f"no end of headers after byte {at}")
        lines = data[at:end].decode("utf-8", "replace").split("\r\n")[1:]
        headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}
        n = int(headers.get("content-length", "-1"))
        if n < 0 or end + 4 + n > total:
            raise ValueError(f"bad Content-Length at byte {at}")
        yield headers, data[end + 4 : end + 4 + n]
        at = end + 4 + n


def read_segments(spark: SparkSession, path: str) -> DataFrame:
    """One row per record: origin, record_type, segment, total_length, uri, digest (hex), refers_to, block."""
    files = spark.read.format("binaryFile").load(path).select("content")
    schema = "origin string, record_type string, segment int, total_length long, uri string, digest string, refers_to string, block binary"

    def parse(batches: Iterator) -> Iterator:
        import pyarrow as pa

        names = [x.split()[0] for x in schema.split(", ")]
        kinds = [pa.string(), pa.string(), pa.int32(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.binary()]
        for b in batches:
            for content in b.column(0):
                data = content.as_py()
                data = gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data
                rows, held = [], 0
                for h, block in parse_stream(data):
                    sha = h.get("warc-payload-digest", "").removeprefix("sha1:")
                    bare = lambda x: x and x.strip("<>").removeprefix(URN)
                    total = h.get("warc-segment-total-length")
                    rows.append((bare(h.get("warc-segment-origin-id") or h.get("warc-record-id")), h.get("warc-type"), int(h.get("warc-segment-number", 0)), int(total) if total else None, h.get("warc-target-uri"), base64.b32decode(sha).hex() if sha else None, bare(h.get("warc-refers-to")), block))
                    held += len(block)
                    if held > 4 << 20:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)
                        rows, held = [], 0
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)

    return files.mapInArrow(parse, schema)


def _decode(record_type: str, segments: list[tuple[int, bytes]], total: int | None, digest: str | None):
    """(payload or None, its bytes, its SHA-1, ok)."""
    segments.sort(key=lambda s: s[0])
    numbers, block = [s[0] for s in segments], b"".join(s[1] for s in segments)
    whole = numbers == [0] or (numbers == list(range(1, len(numbers) + 1)) and total == len(block))
    head, gap, body = block.partition(b"\r\n\r\n")
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(b":") for x in head.split(b"\r\n")[1:])}
    if record_type == "revisit":
        return None, int(fields.get(b"content-length", b"0")), digest, bool(gap) and digest is not None
    payload = (dechunked(body) if fields.get(b"transfer-encoding", b"").lower() == b"chunked" else body) if whole and gap else None
    if payload is None:
        return None, None, None, False
    sha = hashlib.sha1(payload).hexdigest()
    return payload, len(payload), sha, sha == digest


def reassemble(segments: DataFrame, with_payload: bool = True) -> DataFrame:
    """One row per origin record: key, record_type, uri, payload, payload_bytes, payload_digest, refers_to, ok."""
    schema = "key string, record_type string, uri string, payload_bytes long, payload_digest string, refers_to string, ok boolean" + (", payload binary" if with_payload else "")
    names = [x.strip().split()[0] for x in schema.split(",")]

    def row(key, kind, uri, parts, total, digest, refers):
        payload, n, sha, ok = _decode(kind, parts, total, digest)
        return (key.partition("/")[0] or None, kind, uri, n, sha, refers, ok, *((payload,) if with_payload else ()))

    def single(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame([row(o, k, u, [(0, bytes(x))], None, d, r) for o, k, u, d, r, x in zip(b.origin, b.record_type, b.uri, b.digest, b.refers_to, b.block)], columns=names)

    def joined(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame([row(o, k, u, [(s["segment"], bytes(s["block"])) for s in parts], None if pd.isna(t) else int(t), d, None) for o, k, u, d, t, parts in zip(b.origin, b.record_type, b.uri, b.digest, b.total_length, b.parts)], columns=names)

    alone = segments.where("segment = 0").mapInPandas(single, schema)
    first = F.when(F.col("segment") == 1, F.struct("record_type", "uri", "digest"))
    groups = segments.where("segment > 0").groupBy("origin").agg(F.max(first).alias("f"), F.max("total_length").alias("total_length"), F.collect_list(F.struct("segment", "block")).alias("parts"))
    groups = groups.select("origin", F.coalesce("f.record_type", F.lit("response")).alias("record_type"), "f.uri", "f.digest", "total_length", "parts")
    return alone.unionByName(groups.mapInPandas(joined, schema))


def round_trip(pages: DataFrame, path: str | None = None, **options) -> DataFrame:
    """Write ``pages`` (page_id, url, html) as archives, read them back and reassemble."""
    spark = pages.sparkSession
    path = path or work_path(spark, "archive")
    write_archives(pages.select(F.col("page_id").alias("key"), F.col("url").alias("uri"), F.col("html").cast("binary").alias("payload")), path, **options)
    return reassemble(read_segments(spark, path), with_payload=False)
