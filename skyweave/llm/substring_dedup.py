"""Substring deduplication: Rabin-Karp hashes of every window of ``width`` words, counted over the corpus.

Map side, each block of texts hashes all its windows. A window's anchor is the smallest hashed 8-gram in it, so equal
windows have equal anchors at equal offsets; consecutive windows with one anchor travel as one run: 64 bits of the
anchor and 48 bits of each window's own hash identify a window. Within a block a window is sent once (its earliest
occurrence; later ones are known to be repeats), which pre-aggregates passages that a third of all documents share:
a bucket gets a window at most once from each block. Buckets find repeats by sorting, and the repeated windows come back
as (doc_id, start, length) runs that merge into maximal removal intervals on the document.

Edge cases: null and empty texts and texts shorter than a window have no window; a null doc_id sorts before all others; rows that
share a doc_id, or have none, are documents of their own in the order of a hash of their texts; rows equal in both are one document and do not repeat each
other; extra columns stay, one named like an added column is replaced by it."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

ANCHOR = 8
_INDEX = (1 << 24) - 1
_RUNS = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n", pa.int64())])
_SENT = pa.schema([("bucket", pa.int32()), *((c, pa.binary()) for c in ("anchor", "doc", "start", "n", "off", "window"))])


def repeats(anchor, off, window, doc, start) -> np.ndarray:
    """Mask of the windows that occur at an earlier (doc, start); rows must be in that order."""
    key = C.mix(anchor ^ (window * C.U64(0xD6E8FEB86659FD93)) ^ (off.astype(C.U64) << C.U64(57)))
    order = np.argsort(key, kind="stable")
    k = key[order]
    same = k[1:] == k[:-1]
    i, j = order[1:], order[:-1]
    if not np.array_equal(same, same & (anchor[i] == anchor[j]) & (window[i] == window[j]) & (off[i] == off[j])):
        order = np.lexsort((off, window, anchor))  # two identities share a sort key: compare them in full
        i, j = order[1:], order[:-1]
        same = (anchor[i] == anchor[j]) & (window[i] == window[j]) & (off[i] == off[j])
    out = np.zeros(len(key), bool)
    if not len(key):
        return out
    first = np.maximum.accumulate(np.where(np.concatenate(([True], ~same)), np.arange(len(order)), 0))
    head = order[first]
    out[order] = (doc[order] != doc[head]) | (start[order] != start[head])
    return out


def runs(doc, start) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of consecutive starts of a document; rows in (doc, start) order."""
    if not len(doc):
        return doc, start, start
    new = np.concatenate(([True], (doc[1:] != doc[:-1]) | (start[1:] - start[:-1] > 1)))
    at = np.flatnonzero(new)
    last = np.concatenate((at[1:], [len(doc)])) - 1
    return doc[at], start[at], start[last] - start[at] + 1


def _windows(docs: list[tuple[int, int, list[bytes]]], width: int):
    """anchor, off, window, doc, start of all windows of (doc_id, first word, words) pieces in that order."""
    h = np.concatenate([C.hashed(w) for _, _, w in docs])
    sizes = np.array([len(w) for _, _, w in docs])
    ends = np.cumsum(sizes)
    k = min(ANCHOR, width)
    grams, own = C.rolling(h, k), C.rolling(h, width)
    low = (grams & C.U64(~_INDEX & (1 << 64) - 1)) | np.arange(len(grams), dtype=C.U64)
    span, have = width - k + 1, 1
    while have < span:  # sliding minimum by doubling
        step = min(have, span - have)
        low = np.minimum(low[:-step], low[step:])
        have += step
    owner = np.repeat(np.arange(len(docs)), sizes)
    at = np.arange(len(own))
    at = at[at + width <= ends[owner[: len(own)]]]
    piece = owner[at]
    p = (low[at] & C.U64(_INDEX)).astype(np.int64)
    doc = np.array([d for d, _, _ in docs], np.int64)[piece]
    start = at - (ends - sizes)[piece] + np.array([s for _, s, _ in docs], np.int64)[piece]
    return grams[p], p - at, own[at] & C.U64((1 << 48) - 1), doc, start


def _sender(width: int, buckets: list[int], block_bytes: int):
    def flush(docs):
        docs.sort(key=lambda d: d[:2])
        anchor, off, window, doc, start = _windows(docs, width)
        again = repeats(anchor, off, window, doc, start)
        d, s, n = runs(doc[again], start[again])
        if len(d):
            to = buckets[int(d[0]) % len(buckets)]
            yield C.batch_of(_SENT, bucket=[to], anchor=[b""], doc=[d.tobytes()], start=[s.tobytes()], n=[n.tobytes()], off=[b""], window=[b""])
        anchor, off, window, doc, start = (x[~again] for x in (anchor, off, window, doc, start))
        if not len(anchor):
            return
        new = np.concatenate(([True], (anchor[1:] != anchor[:-1]) | (doc[1:] != doc[:-1]) | (start[1:] != start[:-1] + 1) | (off[1:] != off[:-1] - 1)))
        at = np.flatnonzero(new)
        n = np.diff(np.concatenate((at, [len(anchor)])))
        bucket = (C.mix(anchor[at]) % C.U64(len(buckets))).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        edges = np.searchsorted(bucket[order], np.arange(len(buckets) + 1))
        bytes6 = window.view(np.uint8).reshape(-1, 8)[:, :6]
        rows = {c: [] for c in _SENT.names}
        for b in range(len(buckets)):
            runs_of = order[edges[b] : edges[b + 1]]
            if not len(runs_of):
                continue
            i, m = at[runs_of], n[runs_of]
            each = np.repeat(i - np.concatenate(([0], np.cumsum(m)[:-1])), m) + np.arange(m.sum())
            first = int(doc[i[0]])
            rows["bucket"].append(buckets[b])
            rows["anchor"].append(anchor[i].tobytes())
            rows["doc"].append(first.to_bytes(8, "little", signed=True) + C.pack(np.diff(doc[i], prepend=first).view(np.uint64)))
            rows["start"].append(C.pack(start[i]))
            rows["n"].append(C.pack(m))
            rows["off"].append(C.pack(off[i]))
            rows["window"].append(np.ascontiguousarray(bytes6[each]).tobytes())
        yield C.batch_of(_SENT, **rows)

    def run(batches):
        for block in C.blocks(batches, block_bytes):
            docs, size = [], 0
            for i, t in block:
                words = (t or b"").split()
                for lo in range(0, max(1, len(words) - width + 1), 1 << 22):  # a huge text goes in overlapping pieces
                    piece = words[lo : lo + (1 << 22) + width - 1]
                    if len(piece) >= width:
                        docs.append((i, lo, piece))
                        size += len(piece)
                        if size >= 1 << 22:
                            yield from flush(docs)
                            docs, size = [], 0
            if docs:
                yield from flush(docs)

    return run


def _finder(batches):
    """Repeats among all windows of the partition's buckets."""
    parts = {c: [] for c in ("anchor", "off", "window", "doc", "start", "n")}
    for batch in batches:
        for row in batch.to_pylist():
            if not row["anchor"]:
                yield C.batch_of(_RUNS, **{c: np.frombuffer(row[k], np.int64) for c, k in (("doc_id", "doc"), ("start", "start"), ("n", "n"))})
                continue
            parts["anchor"].append(np.frombuffer(row["anchor"], C.U64))
            first = int.from_bytes(row["doc"][:8], "little", signed=True)
            parts["doc"].append(np.cumsum(C.unpack(row["doc"][8:])) + first)
            for c in ("start", "n", "off"):
                parts[c].append(C.unpack(row[c]))
            parts["window"].append(np.frombuffer(row["window"], np.uint8))
    if not parts["anchor"]:
        return
    raw = np.concatenate(parts.pop("window")).reshape(-1, 6)
    p = {c: np.concatenate(v) for c, v in parts.items()}
    parts.clear()
    head = np.cumsum(p["n"]) - p["n"]
    order = np.lexsort((p["start"], p["doc"]))
    n = p["n"][order]
    rank = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    each = np.repeat(head[order], n) + rank
    wide = np.zeros((len(raw), 8), np.uint8)
    wide[:, :6] = raw
    window = wide.view(C.U64).ravel()[each]
    del wide, raw
    anchor, doc = np.repeat(p["anchor"][order], n), np.repeat(p["doc"][order], n)
    start, off = np.repeat(p["start"][order], n) + rank, np.repeat(p["off"][order], n) - rank
    again = repeats(anchor, off, window, doc, start)
    again = np.flatnonzero(again)
    again = again[np.lexsort((start[again], doc[again]))]  # runs of one document may overlap in start order
    d, s, m = runs(doc[again], start[again])
    for lo in range(0, len(d), 500_000):
        yield C.batch_of(_RUNS, doc_id=d[lo : lo + 500_000], start=s[lo : lo + 500_000], n=m[lo : lo + 500_000])


def repeated_windows(docs: DataFrame, width: int = 20, block_bytes: int = 6 << 20) -> DataFrame:
    """(doc_id, start, n): runs of n consecutive window starts whose windows occur earlier in the corpus; the ids of ``docs`` are those of its different rows."""
    spark = docs.sparkSession
    buckets = C.partition_keys(spark, C.exchange_width(docs))
    sent = C.keyed_docs(docs).mapInArrow(C.task(_sender(width, buckets, block_bytes)), "bucket int, anchor binary, doc binary, start binary, n binary, off binary, window binary")
    return sent.repartition(len(buckets), "bucket").mapInArrow(C.task(_finder), "doc_id long, start long, n long")


def covered(n_words: int, found: list[dict] | None, width: int) -> np.ndarray:
    """Mask of the words inside a removed window."""
    d = np.zeros(n_words + 1, np.int32)
    for r in found or ():
        lo, hi = r["start"], r["start"] + r["n"] + width - 1
        if lo < n_words:
            d[lo] += 1
            d[min(hi, n_words)] -= 1
    return np.cumsum(d[:-1]) > 0


def deduplicate(docs: DataFrame, width: int = 20) -> DataFrame:
    """All columns of ``docs`` with removed words taken out of text, plus ``n_words``, ``n_removed`` and ``removed``,
    the maximal removal intervals as an array of (start, end) word positions. Kept words are joined by one space if
    anything was removed; other texts stay as they are. A null text stays null."""
    rows, _ = C.row_keys(docs)
    marked = repeated_windows(C.keyed_rows(rows), width).groupBy("doc_id").agg(F.collect_list(F.struct("start", "n")).alias("_found")).select(F.col("doc_id").alias(C.ROW), "_found")
    names = [c for c in docs.columns if c != "text"]
    joined = rows.select(F.struct(*names).alias("_rest"), F.col("text").cast("string").alias("text"), C.ROW).join(marked, C.ROW, "left").select("_rest", "text", "_found")
    rest = joined.schema["_rest"].dataType

    def run(batches):
        for batch in batches:
            out = {c: [] for c in ("text", "n_words", "n_removed", "removed", "kept_sha256")}
            for t, found in zip(C.texts(batch), batch.column(2).to_pylist()):
                words = (t or b"").split()
                gone = covered(len(words), found, width) if found else None
                if gone is not None and gone.any():
                    step = np.flatnonzero(np.diff(np.concatenate(([0], gone.view(np.int8), [0]))))
                    spans = [{"start": int(a), "end": int(b)} for a, b in zip(step[::2], step[1::2])]
                    kept = b" ".join([w for w, g in zip(words, gone.tolist()) if not g])
                    text = kept
                else:
                    spans, kept, text = [], b" ".join(words), t
                out["text"].append(text)
                out["n_words"].append(len(words))
                out["n_removed"].append(int(gone.sum()) if gone is not None else 0)
                out["removed"].append(spans)
                out["kept_sha256"].append(hashlib.sha256(kept).hexdigest())
            yield pa.record_batch([batch.column(0), pa.array(out["text"], pa.binary()).cast(pa.string()), pa.array(out["n_words"], pa.int64()), pa.array(out["n_removed"], pa.int64()), pa.array(out["removed"], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), pa.array(out["kept_sha256"], pa.string())], names=["_rest", "text", "n_words", "n_removed", "removed", "kept_sha256"])

    made = joined.mapInArrow(C.task(run), f"_rest {rest.simpleString()}, text string, n_words long, n_removed long, removed array<struct<start:bigint,end:bigint>>, kept_sha256 string")
    added = ("n_words", "n_removed", "removed", "kept_sha256")
    return made.select(*(F.col(f"_rest.`{c}`") if c != "text" else F.col("text") for c in docs.columns if c not in added), *added)


def op2_substring_dedup(spark, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text")
    return deduplicate(docs, 20).select("doc_id", "n_words", "n_removed", "kept_sha256")


ORACLE = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
win AS (SELECT doc_id, s, array_to_string(ws[s:s+19], ' ') AS k FROM w, unnest(range(1, len(ws) - 18)) AS u(s)),
bad AS (SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY k ORDER BY doc_id, s) AS rn FROM win) WHERE rn > 1),
cov AS (SELECT DISTINCT doc_id, p FROM bad, unnest(range(s, s + 20)) AS v(p)),
gone AS (SELECT doc_id, list(p) AS ps, count(*) AS n FROM cov GROUP BY doc_id),
ex AS (SELECT w.doc_id, i, ws[i] AS word FROM w, unnest(range(1, len(ws) + 1)) AS t(i)),
kept AS (SELECT ex.doc_id, string_agg(word, ' ' ORDER BY i) AS k FROM ex ANTI JOIN cov ON ex.doc_id = cov.doc_id AND ex.i = cov.p GROUP BY ex.doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(gone.n, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept.k, '')) AS kept_sha256
FROM w LEFT JOIN gone ON w.doc_id = gone.doc_id LEFT JOIN kept ON w.doc_id = kept.doc_id
"""
