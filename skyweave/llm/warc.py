"""WARC archives: a writer with payload deduplication and a splittable reader.

Each record is a gzip member of its own. The reader cuts archives into byte ranges; a task scans its range for the gzip magic,
takes a position for a member only if it inflates to a WARC version line, and owns the records that start in
its range, reading past the end of the range to finish the last. Nothing is indexed and no archive is read by one task.

Size and digest of a response are those of the payload that was read, and a payload that does not have its header's digest is an
error; a revisit has no payload, so its header gives both. Archives of other writers are read as well: header names in any case, ids of any form
(``page_id`` is null then, ``record_id`` has them whole), records of all types; a block that is no HTTP message is the payload.

Edge cases: a null html is an empty payload. Response or revisit is decided for each (page_id, payload): a page with a null
page_id is written with an empty id, read back as null, and comes after all others when the response of equal payloads is chosen; rows that
share both the smallest page_id and the payload are all responses, and so are equal payloads without any id; one page_id with several payloads is decided for
each. A truncated last member is reported by an error; empty tables give no archive and no row; extra columns are ignored."""

from __future__ import annotations

import base64
import hashlib
import re
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

MAGIC = b"\x1f\x8b\x08"
_RECORD = "page_id long, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, payload binary, record_id string, refers_to_id string"
_PAGE = re.compile(r"<urn:page:(-?\d+)>")


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def member(raw: bytes, level: int = 1) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(raw) + z.flush()


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, refers_uri: str | None, revisit: bool) -> bytes:
    """A response record with its payload, or a revisit record with the HTTP head alone."""
    digest = base32_sha1(payload)
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    body = http if revisit else http + payload
    lines = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", "WARC-Date: 2024-01-01T00:00:00Z"]
    if url is not None:
        lines.append("WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"))
    lines += [f"WARC-Payload-Digest: sha1:{digest}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}"]
    if revisit:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{'' if refers_to is None else refers_to}>"]
    return ("\r\n".join(lines) + "\r\n\r\n").encode() + body + b"\r\n\r\n"


def write(pages: DataFrame, folder: str, least_bytes: int = 0, part_bytes: int = 64 << 20) -> DataFrame:
    """Write every page to archives of about ``part_bytes`` of compressed records in ``folder``; returns (path, length).

    Of equal payloads of at least ``least_bytes`` bytes the one with the smallest page_id is the response. Only ids, sizes and
    digests are shuffled to find it; pages then meet their decision by all three."""
    html = F.coalesce(F.col("html").cast("string"), F.lit(""))
    same = (F.sha1(html.cast("binary")).alias("sha"), F.octet_length(html).alias("n"))
    p = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), html.alias("html"), *same)
    light = p.select("page_id", "sha", "n").where(F.col("n") >= least_bytes).distinct()
    first = light.groupBy("sha", "n").agg(F.min("page_id").alias("first"))  # null ids do not count
    twins = light.join(first, ["sha", "n"]).where("first is not null and not page_id <=> first").select(F.col("page_id").alias("_id"), F.col("sha").alias("_sha"), F.col("n").alias("_n"), "first")
    decided = p.join(twins, F.col("page_id").eqNullSafe(F.col("_id")) & (F.col("sha") == F.col("_sha")) & (F.col("n") == F.col("_n")), "left").select("page_id", "url", "html", "first")
    names = {"folder": folder}

    def run(batches):
        import uuid

        fs, at = C.local_path(names["folder"])
        fs.create_dir(at, recursive=True)
        out, path, size = None, None, 0
        made = []
        for batch in batches:
            cols = [batch.column(i).to_pylist() for i in (0, 1, 3)]
            for i, url, ref, html in zip(*cols, C.texts(batch, "html")):
                if out is None:
                    # a retried or speculative task writes a file of its own; only files that a task returns are read
                    path, size = f"{at}/part-{uuid.uuid4().hex}.warc.gz", 0
                    out = fs.open_output_stream(path, compression=None)
                raw = member(record(i, url, html, ref, None, ref is not None))
                out.write(raw)
                size += len(raw)
                if size >= part_bytes:
                    out.close()
                    made.append((path, size))
                    out = None
        if out is not None:
            out.close()
            made.append((path, size))
        yield pa.record_batch([pa.array([m[0] for m in made], pa.string()), pa.array([m[1] for m in made], pa.int64())], names=["path", "length"])

    return C.cut(decided.mapInArrow(run, "path string, length long"))


def starts(window: bytes, limit: int) -> list[int]:
    """Positions below ``limit`` of gzip members that inflate to a WARC version line."""
    out, at = [], window.find(MAGIC)
    while 0 <= at < limit:
        try:
            if zlib.decompressobj(31).decompress(window[at : at + 512], 8)[:5] == b"WARC/":
                out.append(at)
        except zlib.error:
            pass
        at = window.find(MAGIC, at + 1)
    return out


def _fields(lines: list[bytes]) -> dict[str, str]:
    """Header fields by lower-case name; lines that begin with white space continue the field before them."""
    out: dict[str, str] = {}
    name = None
    for line in lines:
        if line[:1] in (b" ", b"\t") and name:
            out[name] += " " + line.decode("utf-8", "replace").strip()
            continue
        k, colon, v = line.decode("utf-8", "replace").partition(":")
        if colon:
            name = k.strip().lower()
            out[name] = v.strip()
    return out


def _page(uri: str | None) -> int | None:
    m = _PAGE.fullmatch(uri or "")
    return int(m[1]) if m else None


def parse(raw: bytes) -> tuple:
    """A record's page_id, url, type, payload size, digest, refers_to, payload (None for a revisit), record id and the id it refers to."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    h = _fields(head.split(b"\r\n")[1:])
    size = int(h["content-length"])
    if len(rest) < size:
        raise ValueError(f"record {h.get('warc-record-id')}: {len(rest)} of {size} bytes")
    payload, said, kind = rest[:size], None, h["warc-type"].lower()
    if payload.startswith(b"HTTP/") and "http" in h.get("content-type", "http"):
        http, _, payload = payload.partition(b"\r\n\r\n")
        length = _fields(http.split(b"\r\n")[1:]).get("content-length", "")
        said = int(length) if length.isdigit() else None
    label, colon, digest = h.get("warc-payload-digest", "").partition(":")
    digest = digest if colon else label
    if kind == "revisit":
        payload, n = None, said
    else:
        n, own = len(payload), base32_sha1(payload)
        if label.lower() == "sha1" and kind == "response" and digest.upper() != own:
            raise ValueError(f"record {h.get('warc-record-id')}: the payload's digest is {own}, its header says {digest}")
        digest = own
    me, other = h.get("warc-record-id"), h.get("warc-refers-to")
    return _page(me), h.get("warc-target-uri"), kind, n, digest or None, _page(other), payload, me, other


def read(spark: SparkSession, files: DataFrame, split_bytes: int = 4 << 20, with_payload: bool = True, chunk: int = 1 << 20) -> DataFrame:
    """Records of the archives in ``files`` (path, length), read by byte ranges of ``split_bytes``."""
    ranges = files.select("path", "length", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.col("length") - 1, F.lit(0)), F.lit(split_bytes).cast("long"))).alias("lo")).repartition(C.shuffle_width(spark), "path", "lo")

    def run(batches):
        for batch in batches:
            for path, length, lo in zip(*(batch.column(i).to_pylist() for i in range(3))):
                yield from _range(path, lo, min(lo + split_bytes, length), length, chunk, with_payload)

    return ranges.mapInArrow(run, _RECORD)


def _range(path, lo, hi, length, chunk, with_payload):
    fs, at = C.local_path(path)
    rows, size = [], 0
    with fs.open_input_file(at) as f:
        overlap = 512
        pos = lo
        while pos < hi:  # find the first member that starts in the range
            window = f.read_at(min(chunk + overlap, length - pos), pos)
            found = starts(window, min(chunk, hi - pos))
            if found:
                pos += found[0]
                break
            pos += chunk
        else:
            return
        data, base = b"", pos
        while pos < hi:
            z, raw = zlib.decompressobj(31), []
            while not z.eof:
                if not data:
                    data = f.read_at(min(chunk, length - base), base)
                    base += len(data)
                    if not data:
                        raise EOFError(f"{path}: the member at {pos} is cut short")
                raw.append(z.decompress(data))
                data = z.unused_data if z.eof else b""
            pos = base - len(data)
            rows.append(parse(b"".join(raw)))
            size += (rows[-1][3] or 0) + 200
            if not with_payload:
                rows[-1] = (*rows[-1][:6], None, *rows[-1][7:])
            if size > 8 << 20:
                yield _records(rows)
                rows, size = [], 0
    if rows:
        yield _records(rows)


def _records(rows):
    c = list(zip(*rows))
    types = (pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.binary(), pa.string(), pa.string())
    return pa.record_batch([pa.array(x, t) for x, t in zip(c, types)], names=["page_id", "url", "record_type", "payload_bytes", "payload_digest", "refers_to", "payload", "record_id", "refers_to_id"])


def op9_warc(spark, sf_dir: str) -> DataFrame:
    files = write(C.table(spark, sf_dir, "pages"), C.scratch(spark, "warc"))
    return read(spark, files, with_payload=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
h AS (SELECT page_id, octet_length(b) AS n, upper(sha1(b)) AS s FROM p),
f AS (SELECT *, min(page_id) OVER (PARTITION BY s, n) AS first FROM h),
d AS (SELECT *, list_transform(range(0, 8), lambda i: CAST('0x' || substr(s, CAST(5 * i + 1 AS INTEGER), 5) AS BIGINT)) AS v FROM f)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes,
array_to_string(list_transform(v, lambda x: array_to_string(list_transform([15, 10, 5, 0], lambda k: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST(((x >> k) & 31) + 1 AS INTEGER), 1)), '')), '') AS payload_digest,
CASE WHEN page_id IS NOT DISTINCT FROM first THEN 'response' ELSE 'revisit' END AS record_type,
CASE WHEN page_id IS NOT DISTINCT FROM first THEN NULL ELSE first END AS refers_to FROM d
"""
