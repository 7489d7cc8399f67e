"""Helpers shared by the training-data operators: table access, deterministic block exchange, window hashes."""

from __future__ import annotations

import ctypes
import os
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

U64 = np.uint64
#: Odd multiplier and its inverse modulo 2**64 for the rolling polynomial (fixed values).
ROLL = 0x9E3779B97F4A7C15
ROLL_INV = pow(ROLL, -1, 1 << 64)
#: Internal stand-in for a null doc_id while rows are keyed; it sorts before every real id.
NULL_ID = -(1 << 63)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shuffle_width(spark: SparkSession) -> int:
    """Partitions of an exchange, as the cluster's operator sized them."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


#: Bytes of text of which a partition of an exchange of texts' contents gets the rows, at most and on average: a Python worker holds them at once.
PART_BYTES = 64 << 20


def exchange_width(docs: DataFrame, row_bytes: int = 0) -> int:
    """Partitions of an exchange of what the texts of ``docs`` hold, besides ``row_bytes`` for each row: as the cluster's operator sized them, or more
    where these would be larger than PART_BYTES."""
    size = docs.agg(F.sum(F.coalesce(F.octet_length(F.col("text").cast("string")), F.lit(0)).cast("long") + row_bytes)).first()[0] or 0
    return max(shuffle_width(docs.sparkSession), -(-size // PART_BYTES))


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Without one a local session (as in tests) gets a folder of its own; a cluster's raises."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not sc.master.startswith("local["):
                raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
            folder = tempfile.mkdtemp(prefix="skyweave-")
        sc.setCheckpointDir(folder)
    return sc._jsc.sc().getCheckpointDir().get()


def scratch(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage with a table written to the shared folder: computed once, where a checkpoint computes its rows twice."""
    path = scratch(df.sparkSession, "table")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bitmap(bits: DataFrame, size: int) -> bytes:
    """A map of 2**size bits with those set that the column ``bit`` of ``bits`` numbers from 1; its size is all that reaches the driver."""
    out = bytearray(1 << size - 3)
    for r in bits.groupBy(F.bitmap_bucket_number("bit").alias("k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("bit")).alias("b")).collect():
        out[(r.k - 1) * 4096 : r.k * 4096] = r.b
    return bytes(out)


def partition_keys(spark: SparkSession, width: int) -> list[int]:
    """One int per hash partition, so that ``repartition(width, key)`` deals bucket i to a partition of its own."""
    found: dict[int, int] = {}
    lo, step = 0, 32 * width
    while len(found) < width:
        ids = spark.range(lo, lo + step, 1, 1).select(F.col("id").cast("int").alias("id"))
        for p, i in ids.groupBy(F.pmod(F.hash("id"), F.lit(width)).alias("p")).agg(F.min("id")).collect():  # one row a partition
            found.setdefault(p, i)
        lo += step
    return [found[p] for p in range(width)]


def keyed_docs(docs: DataFrame, *extra: Column) -> DataFrame:
    """doc_id (null as NULL_ID) and text, plus extra columns."""
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_ID)).alias("doc_id"), F.col("text").cast("string").alias("text"), *extra)


#: Column of ``row_keys``.
ROW = "__row__"


def row_keys(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """``docs`` with a key of each different row, in the order of doc_id with null first: the doc_id itself where no two rows share one, and else the place of
    (doc_id, 128 bits of the text) among all; then also the table of keys and their ids (as NULL_ID for null). Rows equal in both share a key."""
    at = F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_ID))
    if not docs.select(at.alias("_id")).groupBy("_id").count().where("count > 1").limit(1).count():
        return docs.withColumn(ROW, at), None
    said = [at.alias("_id"), F.xxhash64(F.col("text").cast("string")).alias("_t1"), F.xxhash64(F.lit(1), F.col("text").cast("string")).alias("_t2")]
    ids_ = cut(docs.select(*said).distinct().orderBy("_id", "_t1", "_t2").withColumn(ROW, F.monotonically_increasing_id()))
    rest = docs.select(F.struct(*docs.columns).alias("_whole"), *said).join(ids_, ["_id", "_t1", "_t2"])
    return rest.select(*(F.col(f"_whole.`{c}`") for c in docs.columns), ROW), ids_.select(ROW, "_id")


def keyed_rows(rows: DataFrame) -> DataFrame:
    """The row key as doc_id, and text."""
    return rows.select(F.col(ROW).alias("doc_id"), F.col("text").cast("string").alias("text"))


def restored_id(name: str = "doc_id") -> Column:
    return F.when(F.col(name) != F.lit(NULL_ID), F.col(name)).alias(name)


def held_out(modulus: int, remainder: int, column: str = "doc_id") -> Column:
    """crc32 of the id's decimal text modulo ``modulus`` equals ``remainder``; false for a null id."""
    return F.coalesce(F.pmod(F.crc32(F.col(column).cast("string")), F.lit(modulus)) == remainder, F.lit(False))


def texts(batch: pa.RecordBatch, name: str = "text") -> list[bytes | None]:
    """The column, or the field of the first column, a struct of whole rows, so that long texts travel once."""
    at = batch.schema.get_field_index(name)
    column = batch.column(at) if at >= 0 else batch.column(0).field(name)
    return column.cast(pa.binary()).to_pylist()


def ids(batch: pa.RecordBatch, name: str = "doc_id") -> np.ndarray:
    return batch.column(batch.schema.get_field_index(name)).to_numpy(zero_copy_only=False)


class Memo(dict):
    """A dict that computes what is missing and starts afresh when it has ``most`` entries."""

    def __init__(self, fn, most: int = 400_000):
        super().__init__()
        self.fn, self.most = fn, most

    def __missing__(self, key):
        if len(self) >= self.most:
            self.clear()
        self[key] = value = self.fn(key)
        return value


_kept: list[Memo] = []


def task_memo(fn) -> Memo:
    """A memo of a module, emptied when a task ends."""
    _kept.append(Memo(fn))
    return _kept[-1]


word_hash = task_memo(lambda w: xxhash.xxh3_64_intdigest(w, 7))


def release() -> None:
    """Give back what a task remembered: a Python worker outlives it and serves the stages that follow."""
    for memo in _kept:
        memo.clear()
    _powers[:] = [np.ones(1, U64), np.ones(1, U64)]
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # only glibc has it
        pass


def task(fn: Callable, most_rows: int = 1000) -> Callable:
    """``fn`` for mapInArrow: it gets, and sends on, at most ``most_rows`` rows at a time, and its worker keeps nothing afterwards."""

    def slices(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, most_rows):
                yield batch.slice(lo, most_rows)

    def run(batches):
        try:
            yield from fn(slices(batches))
        finally:
            release()

    return run


def hashed(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(word_hash.__getitem__, words), U64, len(words))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit values."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


_powers: list[np.ndarray] = [np.ones(1, U64), np.ones(1, U64)]


def rolling(h: np.ndarray, width: int) -> np.ndarray:
    """Rabin-Karp hash of every ``width`` consecutive values (mod 2**64), one per start."""
    n = len(h)
    if n < width:
        return np.empty(0, U64)
    if len(_powers[0]) < n + 1:
        size = max(n + 1, 1 << 16)
        for i, b in enumerate((ROLL, ROLL_INV)):
            p = np.full(size, b, U64)
            p[0] = 1
            _powers[i] = np.cumprod(p, dtype=U64)
    up, down = _powers
    prefix = np.zeros(n + 1, U64)
    np.cumsum(h * down[:n], dtype=U64, out=prefix[1:])
    return mix((prefix[width:] - prefix[:-width]) * up[width - 1 : n])


def shingles(words: list[bytes], width: int) -> np.ndarray:
    """Sorted distinct shingle hashes; the whole sequence is the one shingle of a shorter text, no word gives none."""
    if not words:
        return np.empty(0, U64)
    h = hashed(words)
    if len(words) < width:
        return mix(rolling(h, len(words)) + U64(len(words)))
    return np.unique(rolling(h, width))


def blocks(batches: Iterable[pa.RecordBatch], most_bytes: int) -> Iterator[list[tuple[int, bytes | None]]]:
    """Consecutive (doc_id, text) rows in lists of about ``most_bytes`` of text; a longer text is a list of its own."""
    out, size = [], 0
    for batch in batches:
        for i, t in zip(ids(batch).tolist(), texts(batch)):
            out.append((i, t))
            size += len(t or b"") + 16
            if size >= most_bytes:
                yield out
                out, size = [], 0
    if out:
        yield out


def smallest(x: np.ndarray) -> np.ndarray:
    """The same non-negative integers in the smallest unsigned type."""
    top = int(x.max()) if len(x) else 0
    return x.astype(np.uint8 if top < 1 << 8 else np.uint16 if top < 1 << 16 else np.uint32 if top < 1 << 32 else np.uint64)


def pack(x: np.ndarray) -> bytes:
    """An unsigned array as bytes, its item size first."""
    x = smallest(x)
    return bytes([x.itemsize]) + x.tobytes()


def unpack(b: bytes) -> np.ndarray:
    return np.frombuffer(b, f"u{b[0]}", offset=1).astype(np.int64)


#: Rows of one key from which it may be hot.
HOT = 1000


def join_counted(left: DataFrame, right: DataFrame, key: str, total: int) -> DataFrame:
    """Inner join of ``left`` with one row of ``right`` per key, whose column ``n`` tells its rows on the left. Keys with more than
    ``total`` / 500 of these, at most 500, are broadcast, so that no task gets all rows of one key; the others are shuffled."""
    if total <= HOT:
        return left.join(right, key)
    hot = right.where(F.col("n") > max(HOT, total / 500)).collect()
    if not hot:
        return left.join(right, key)
    small = F.broadcast(left.sparkSession.createDataFrame(hot, right.schema))
    rest = left.join(F.broadcast(small.select(key)), key, "left_anti").join(right, key)
    return left.join(small, key).unionByName(rest)


def connected(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(node, root): the smallest node reachable from each node of ``edges`` (u, v).

    Alternating star contraction; every round is two aggregations and joins on a written table, and stops when
    every edge already points from a node to a root. Hubs are reduced by min and met by broadcast, never gathered."""
    e = cut(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u != v").distinct())
    while True:
        total = 2 * e.count()
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least("u", F.min("v")).alias("m"), F.count("*").alias("n"))
        large = join_counted(both, low, "u", total).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = cut(large.where("u != v").distinct())
        small = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
        after = join_counted(large, small, "u", total).select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("x")).select("x.u", "x.v")
        e = cut(after.where("u != v").distinct())
        # a forest of stars: no node has two parents and no parent has a parent
        parents = e.groupBy("u").agg(F.count("*").alias("n"))
        if not parents.where("n > 1").limit(1).count() and not e.select(F.col("v").alias("u")).distinct().join(parents, "u", "left_semi").limit(1).count():
            return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def batch_of(schema: pa.Schema, **columns) -> pa.RecordBatch:
    return pa.record_batch([pa.array(columns[f.name], type=f.type) for f in schema], schema=schema)


def local_path(uri: str) -> tuple:
    """(pyarrow filesystem, path) of a URI or a plain path."""
    import pyarrow.fs as pafs

    if "://" not in uri and not uri.startswith("file:"):
        return pafs.LocalFileSystem(), os.path.abspath(uri)
    if uri.startswith("file:"):
        return pafs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return pafs.FileSystem.from_uri(uri)
