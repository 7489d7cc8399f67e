"""Byte-level BPE over the corpus by a global shuffle of distinct words.

A word here is a run without white space, with the one space before it, or a white-space run as the pattern splits it;
no pre-token crosses such a border, so its ids are those of its pre-tokens in turn. Each block of texts becomes a skeleton (one
code per word position, by document) and its distinct words. Words that are one rank of the fixed vocabulary are coded in
place; all others go to their hash bucket, which encodes each distinct word of the corpus once and sends the ids back to the
blocks; the block reassembles its documents by position. Decoding looks the ids up in the token-byte table.

Edge cases: null and empty texts have no token; a null doc_id stays null; rows with equal ids and texts give equal rows;
extra columns are ignored. The library's own tables bound what is held: the vocabulary has a fixed size."""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

#: Unicode White_Space, as the pattern's \s (fixed values).
SPACE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
SPLIT = re.compile(f" ?[^{SPACE}]+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+")
_SCHEMA = "block string, kind int, bucket int, a binary, b binary, c binary"
_NAMES = ["block", "kind", "bucket", "a", "b", "c"]


@lru_cache(2)
def ranks(path: str) -> dict[bytes, int]:
    import pyarrow.fs  # noqa: F401

    fs, p = C.local_path(path)
    with fs.open_input_stream(p, compression=None) as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f.read().splitlines())}


@lru_cache(2)
def encoder(path: str):
    import tiktoken
    from public_tokenizers import PATTERN

    return tiktoken.Encoding("byte_bpe", pat_str=PATTERN, mergeable_ranks=ranks(path), special_tokens={})


@lru_cache(2)
def byte_table(path: str) -> list[bytes]:
    r = ranks(path)
    out = [b""] * (max(r.values()) + 1)
    for k, v in r.items():
        out[v] = k
    return out


@lru_cache(2)
def single_words(path: str) -> dict[str, int]:
    """The ranks that are one word of SPLIT and one pre-token."""
    enc, out = encoder(path), {}
    for k, v in ranks(path).items():
        try:
            w = k.decode()
        except UnicodeDecodeError:
            continue
        if SPLIT.fullmatch(w) and enc.encode_ordinary(w) == [v]:
            out[w] = v
    return out


def default_ranks() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def _block(docs, path):
    """Block key, words by document, and the codes of the words: ids below the vocabulary's size, then block-local words."""
    single = single_words(path)
    base = len(byte_table(path))
    own: dict[str, int] = {}
    code = C.Memo(lambda w: single[w] if w in single else base + own.setdefault(w, len(own)), 1 << 62)
    key, codes = xxhash.xxh3_128(), []
    for i, t in docs:
        key.update(b"%d %d " % (i, -1 if t is None else len(t)))
        key.update(t or b"")
        words = SPLIT.findall(t.decode()) if t else []
        codes.append(np.fromiter(map(code.__getitem__, words), np.int64, len(words)))
    return key.hexdigest(), codes, list(own)


def _words(path: str, buckets: list[int], block_bytes: int):
    def run(batches):
        for docs in C.blocks(batches, block_bytes):
            key, _, own = _block(docs, path)
            by: list[list[int]] = [[] for _ in buckets]
            raw = [w.encode() for w in own]
            for j, w in enumerate(raw):
                by[zlib.crc32(w) % len(buckets)].append(j)
            rows = [(key, 1, buckets[b], C.pack(np.diff(np.array(js), prepend=0)), C.pack(np.array([len(raw[j]) for j in js])), b"".join([raw[j] for j in js])) for b, js in enumerate(by) if js]
            yield _batch(rows)

    return run


def _batch(rows) -> pa.RecordBatch:
    """Rows whose last three values are compressed one by one, as both exchanges carry little else."""
    z = zstandard.ZstdCompressor(level=3)
    cols = list(zip(*((*r[:3], *map(z.compress, r[3:])) for r in rows))) or [()] * 6
    return pa.record_batch([pa.array(c, t) for c, t in zip(cols, (pa.string(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary()))], names=_NAMES)


def _planes(x: np.ndarray) -> bytes:
    """The lowest byte of every value, then the next, as such planes compress better."""
    return np.ascontiguousarray(x.view(np.uint8).reshape(-1, x.itemsize).T).tobytes()


def _unplaned(b: bytes, kind) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(np.dtype(kind).itemsize, -1).T).view(kind).ravel()


def _skeleton(path: str, block_bytes: int):
    def run(batches):
        for docs in C.blocks(batches, block_bytes):
            key, codes, _ = _block(docs, path)
            flat = np.concatenate(codes) if codes else np.empty(0, np.int64)
            who = np.array([d[0] for d in docs], np.int64)
            yield _batch([(key, 0, -1, who.tobytes(), C.pack(np.array([len(c) for c in codes])), _planes(flat.astype(np.uint32)))])

    return run


def _encode(path: str):
    def run(batches):
        enc = encoder(path)
        known: dict[bytes, np.ndarray] = C.Memo(lambda w: np.array(enc.encode_ordinary(w.decode()), np.uint16 if len(byte_table(path)) < 1 << 16 else np.uint32), 1 << 62)
        expand = zstandard.ZstdDecompressor().decompress
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                ends, raw = np.cumsum(C.unpack(expand(r["b"]))).tolist(), expand(r["c"])
                got = [known[raw[lo:hi]] for lo, hi in zip([0, *ends], ends)]
                rows.append((r["block"], 1, -1, expand(r["a"]), C.pack(np.array([len(g) for g in got])), _planes(np.concatenate(got))))
            yield _batch(rows)

    return run


def _assemble(path: str, tail):
    """tail(list of (doc_id, ids array)) -> record batch, per block."""

    def finish(rows):
        heads = [r for r in rows if r[1] == 0]
        base, wide = len(byte_table(path)), np.uint16 if len(byte_table(path)) < 1 << 16 else np.uint32
        expand = zstandard.ZstdDecompressor().decompress
        js, ns, xs = [], [], []
        for r in rows[len(heads) :]:
            js.append(np.cumsum(C.unpack(expand(r[3]))))
            ns.append(C.unpack(expand(r[4])))
            xs.append(_unplaned(expand(r[5]), wide))
        j = np.concatenate(js) if js else np.empty(0, np.int64)
        n = np.concatenate(ns) if ns else np.empty(0, np.int64)
        x = np.concatenate(xs).astype(np.int64) if xs else np.empty(0, np.int64)
        size = np.ones(base + int(j.max() + 1 if len(j) else 0), np.int64)
        head = np.zeros_like(size)
        size[base:] = 0
        size[base + j] = n
        head[base + j] = base + np.cumsum(n) - n
        head[:base] = np.arange(base)
        flat_ids = np.concatenate((np.arange(base), x))
        for r in heads:
            who, counts = np.frombuffer(expand(r[3]), np.int64), C.unpack(expand(r[4]))
            codes = _unplaned(expand(r[5]), np.uint32).astype(np.int64)
            if len(codes) and (codes.max() >= len(size) or not size[codes].all()):
                raise RuntimeError("a block's words did not all return: the input's rows came in another order on a second read; write it to a table first")
            cut = np.cumsum(counts)
            for lo in range(0, len(who), 64):  # a few documents at a time
                hi = min(lo + 64, len(who))
                part = codes[(cut[lo - 1] if lo else 0) : cut[hi - 1]]
                m = size[part]
                ends = np.cumsum(m)
                ids = flat_ids[np.repeat(head[part] - (ends - m), m) + np.arange(int(ends[-1]) if len(ends) else 0)]
                at = np.concatenate(([0], ends))[cut[lo:hi] - (cut[lo - 1] if lo else 0)].tolist()
                yield tail([(int(w), ids[a:b]) for w, a, b in zip(who[lo:hi], [0, *at], at)])

    def run(batches):
        rows = []
        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(6))):
                if rows and row[0] != rows[0][0]:
                    yield from finish(rows)
                    rows = []
                rows.append(row)
        if rows:
            yield from finish(rows)

    return run


def _assembled(docs: DataFrame, path: str, tail, schema: str, block_bytes: int) -> DataFrame:
    spark = docs.sparkSession
    buckets = C.partition_keys(spark, C.exchange_width(docs))
    keyed = C.keyed_docs(docs)
    words = keyed.mapInArrow(C.task(_words(path, buckets, block_bytes)), _SCHEMA).repartition(len(buckets), "bucket").mapInArrow(C.task(_encode(path)), _SCHEMA)
    skeleton = keyed.mapInArrow(C.task(_skeleton(path, block_bytes)), _SCHEMA)
    back = skeleton.unionByName(words).repartition(len(buckets), "block").sortWithinPartitions("block", "kind")
    return back.mapInArrow(C.task(_assemble(path, tail)), schema)


def encode(docs: DataFrame, path: str | None = None, block_bytes: int = 8 << 20) -> DataFrame:
    """(doc_id, ids) of every row."""
    def tail(rows):
        return pa.record_batch([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1].astype(np.int32) for r in rows], pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return _assembled(docs, path or default_ranks(), tail, "doc_id long, ids array<int>", block_bytes).select(C.restored_id(), "ids")


def decode(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text) of (doc_id, ids); bytes that are no UTF-8 become U+FFFD. Ids outside the table raise; null ids give null."""
    p = path or default_ranks()

    def run(batches):
        t = byte_table(p)
        for b in batches:
            out = [None if x is None else b"".join([t[i] for i in x]).decode("utf-8", "replace") for x in b.column(1).to_pylist()]
            yield pa.record_batch([b.column(0), pa.array(out, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(C.task(run), "doc_id long, text string")


def digests(docs: DataFrame, path: str | None = None, block_bytes: int = 8 << 20) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): the digest of encode() and of decoding its ids, in one pass."""
    p = path or default_ranks()

    def tail(rows):
        table = byte_table(p)
        names = _decimals(len(table))
        made = [(i, len(x), hashlib.sha256(b" ".join([names[k] for k in ids])).hexdigest(), hashlib.sha256(b"".join([table[k] for k in ids])).hexdigest()) for i, x in rows for ids in (x.tolist(),)]
        c = list(zip(*made))
        return pa.record_batch([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.string()), pa.array(c[3], pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return _assembled(docs, p, tail, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", block_bytes).select(C.restored_id(), "n_tokens", "ids_sha256", "decoded_sha256")


@lru_cache(2)
def _decimals(n: int) -> list[bytes]:
    return [b"%d" % i for i in range(n)]


def op6_byte_bpe(spark, sf_dir: str) -> DataFrame:
    return digests(C.table(spark, sf_dir, "documents").select("doc_id", "text"))
