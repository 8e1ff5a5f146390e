"""WARC archives: a writer with one gzip member per record, and a splittable reader.

Writing: records with equal payloads of at least ``min_revisit`` bytes become
one response (smallest id) and revisits. The digests are grouped first, without
the payloads; only digests seen twice come back as a lookup, broadcast while it
is small and joined by a shuffle beyond that. Each task writes one file under a
name of its own and reports it; readers take files from those reports alone, so
what a lost or repeated attempt leaves behind is never read.

Reading: files are cut into byte ranges, a range is a task's unit. A task scans
its range for the gzip magic, takes an offset as a record only if the bytes
there inflate to a WARC header, owns the records that start inside its range,
and reads past the end of the range to finish the last one.

Defined results: a null payload is empty; a null id is written as ``null`` and
read back as null; rows that share both id and payload are all responses where
the id is the smallest of its payload; payloads of any length are whole; a null
url gives no target header; an empty table gives no records; other columns are
ignored.
"""

from __future__ import annotations

import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from exkit.staging import new_path, stage

MAGIC = b"\x1f\x8b\x08"
MIN_REVISIT = 100
#: Digests seen twice are broadcast up to this many rows (about 60 bytes each).
BROADCAST_DIGESTS = 100_000
RANGE_BYTES = 8 << 20
READ_STEP = 1 << 20
ID = "urn:x-page:"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

WRITTEN = "path string, bytes long, records long"
READ = "path string, at long, record_type string, page_id long, refers_to long, url string, payload_bytes long, payload_digest string, payload binary"


def _store(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path if "://" in path else f"file://{path}" if not path.startswith("file:") else path.replace("file:", "file://", 1))


def record_bytes(page_id, url, payload: bytes, digest: str, refers_to, is_revisit: bool) -> bytes:
    """One record, not yet compressed."""
    lines = ["WARC/1.1", f"WARC-Type: {'revisit' if is_revisit else 'response'}", f"WARC-Record-ID: <{ID}{'null' if page_id is None else page_id}>", "WARC-Date: 2024-01-01T00:00:00Z"]
    if url is not None:
        lines.append("WARC-Target-URI: " + re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url))
    lines += [f"WARC-Payload-Digest: sha256:{digest}", f"WARC-Payload-Length: {len(payload)}"]
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    if is_revisit:
        lines += [f"WARC-Refers-To: <{ID}{refers_to}>", f"WARC-Profile: {PROFILE}"]
    block = http if is_revisit else http + payload
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def _gzip(data: bytes, level: int) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def _writer(root: str, level: int):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = _store(root)
        fs.create_dir(base, recursive=True)
        name, out, size, n = f"part-{uuid.uuid4().hex}.warc.gz", None, 0, 0
        for batch in batches:
            page, url, html, digest, first = (batch.column(i) for i in range(5))
            for p, u, h, d, f in zip(page.to_pylist(), url.to_pylist(), html.cast(pa.binary()), digest.to_pylist(), first.to_pylist(), strict=True):
                out = out or fs.open_output_stream(f"{base}/{name}", compression=None)
                member = _gzip(record_bytes(p, u, h.as_py() or b"", d, f, f is not None and f != p), level)
                out.write(member)
                size, n = size + len(member), n + 1
        if out:
            out.close()
            yield pa.RecordBatch.from_arrays([pa.array([f"{root}/{name}"]), pa.array([size]), pa.array([n])], names=["path", "bytes", "records"])

    return write


def write_archives(pages: DataFrame, root: str, min_revisit: int = MIN_REVISIT, level: int = 3) -> DataFrame:
    """Write (page_id, url, html) as archives below ``root``; returns the staged report of files (path, bytes, records)."""
    raw = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    own = pages.select("page_id", "url", "html", F.sha2(raw, 256).alias("digest"), F.length(raw).alias("n"))
    long_ones = own.where((F.col("n") >= min_revisit) & F.col("page_id").isNotNull())
    twice = stage(long_ones.groupBy("digest").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("c")).where("c > 1").drop("c"), "warc-digests")
    lookup = F.broadcast(twice) if twice.count() <= BROADCAST_DIGESTS else twice
    rows = own.join(lookup, "digest", "left").select("page_id", "url", "html", "digest", "first")
    return stage(rows.mapInArrow(_writer(root, level), WRITTEN), "warc-files")


class _File:
    """Bytes of one archive, read in steps as they are asked for."""

    def __init__(self, path: str):
        fs, name = _store(path)
        self.f = fs.open_input_file(name)
        self.size = self.f.size()

    def at(self, offset: int, n: int) -> bytes:
        return self.f.read_at(min(n, max(0, self.size - offset)), offset) if offset < self.size else b""


def _is_record(f: _File, offset: int) -> bool:
    """Whether a gzip member that begins with a WARC header starts at ``offset``."""
    z = zlib.decompressobj(31)
    try:
        return z.decompress(f.at(offset, 512), 64).startswith(b"WARC/1.")
    except zlib.error:
        return False


def _member(f: _File, offset: int) -> tuple[bytes, int]:
    """The inflated member at ``offset`` and the offset of its end."""
    z, out, at, step = zlib.decompressobj(31), [], offset, 1 << 14
    while not z.eof:
        piece = f.at(at, step)
        if not piece:
            raise EOFError(f"member at {offset} is cut short")
        out.append(z.decompress(piece))
        at, step = at + len(piece), READ_STEP
    return b"".join(out), at - len(z.unused_data)


def _next_record(f: _File, offset: int, end: int) -> int | None:
    """First offset in [offset, end) where a record starts."""
    while offset < end:
        window = f.at(offset, min(READ_STEP, end - offset) + len(MAGIC) - 1)
        hit = window.find(MAGIC)
        while hit >= 0:
            if offset + hit < end and _is_record(f, offset + hit):
                return offset + hit
            hit = window.find(MAGIC, hit + 1)
        offset += READ_STEP
    return None


def parse_record(data: bytes) -> dict:
    """Headers and payload of one record; the digest and length of a response are those of the bytes read."""
    head, _, rest = data.partition(b"\r\n\r\n")
    named = {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in head.decode().split("\r\n")[1:])}
    block = rest[: int(named["content-length"])]
    key = lambda h: None if h is None or h.endswith("null>") else int(h[len(ID) + 1 : -1])
    out = {"record_type": named["warc-type"], "page_id": key(named["warc-record-id"]), "refers_to": key(named.get("warc-refers-to")), "url": named.get("warc-target-uri"), "payload": None}
    if out["record_type"] == "response":
        out["payload"] = block.partition(b"\r\n\r\n")[2]
        out |= {"payload_bytes": len(out["payload"]), "payload_digest": hashlib.sha256(out["payload"]).hexdigest()}
        if named["warc-payload-digest"] != f"sha256:{out['payload_digest']}":
            raise ValueError(f"payload of {named['warc-record-id']} does not match its digest")
        return out
    return out | {"payload_bytes": int(named["warc-payload-length"]), "payload_digest": named["warc-payload-digest"].removeprefix("sha256:")}


def read_range(path: str, start: int, end: int) -> Iterator[dict]:
    """Records of ``path`` that start in [start, end)."""
    f = _File(path)
    at: int | None = start
    while at is not None and at < end:
        if not (f.at(at, 3) == MAGIC and _is_record(f, at)):
            at = _next_record(f, at, end)
            continue
        data, after = _member(f, at)
        yield {"path": path, "at": at} | parse_record(data)
        at = after


def _reader(payloads: bool):
    names = [x.split()[0] for x in READ.split(", ")]
    kinds = [{"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}[x.split()[1]] for x in READ.split(", ")]

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(rows):
            return pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], k) for c, k in zip(names, kinds, strict=True)], names=names)

        rows, size = [], 0
        for batch in batches:
            for path, start, end in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                for r in read_range(path, start, end):
                    rows.append(r if payloads else r | {"payload": None})
                    size += 200 + len(rows[-1]["payload"] or b"")
                    if size > 4 << 20:
                        yield out(rows)
                        rows, size = [], 0
        yield out(rows)

    return read


def read_archives(files: DataFrame, payloads: bool = True, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """Records of the archives in ``files`` (path, bytes): one row each with type, ids, url, payload and its digest."""
    ranges = files.where("bytes > 0").select("path", F.explode(F.sequence(F.lit(0), F.col("bytes") - 1, F.lit(range_bytes))).alias("start"), "bytes")
    ranges = ranges.select("path", "start", F.least(F.col("start") + range_bytes, "bytes").alias("end"))
    n = max(1, int(files.agg(F.sum(F.ceil(F.col("bytes") / range_bytes))).first()[0] or 0))
    return ranges.repartition(min(n, 100_000), "path", "start").mapInArrow(_reader(payloads), READ)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    files = write_archives(pages, new_path(spark, "warc"))
    return read_archives(files, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha256(coalesce(html, '')) AS d FROM pages),
g AS (SELECT d, min(page_id) AS first FROM p WHERE strlen(html) >= 100 GROUP BY d)
SELECT page_id, CAST(strlen(html) AS BIGINT) AS payload_bytes, p.d AS payload_digest,
  CASE WHEN g.first IS NULL OR g.first = page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN g.first <> page_id THEN g.first END AS refers_to
FROM p LEFT JOIN g ON p.d = g.d
"""
