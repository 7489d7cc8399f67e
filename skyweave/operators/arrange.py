"""Blocks of samples that have no place in time yet: one exchange of packed columns, then each interval is put in order by the task that gets it."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skyweave.operators.system import BLOCK, block_batch, pack

#: Samples of an interval up to which it is put in order in memory; longer ones take the samples with t.
LONGEST = 1 << 21
#: Samples that a task of the exchange gets on average, and that one sends at once.
DEALT = 1 << 18
SENT = 1 << 19
#: Buckets whose samples are one batch of a task at most.
ASIDE = 8


class Unplaced:
    """Samples without t: those of an interval follow the columns ``order``, numbers of which the first is a whole one; nulls come first.

    ``rows`` has interval_id and the columns of ``order``; ``place(intervals, columns)`` gives pixels, angles, data and noise ids of samples by arrays. ``tod()`` has the same samples with t:
    where an interval is too long to be sorted in memory, Spark sorts, and the blocks are the same."""

    def __init__(self, rows: DataFrame, order: tuple[str, ...], place: Callable, tod: Callable[[], DataFrame]):
        self.sparkSession, self.rows, self.order, self.place, self.tod = rows.sparkSession, rows.select(F.col("interval_id").cast("long"), *order), order, place, tod

    @contextmanager
    def planned(self) -> Iterator[None]:
        """Within it the blocks are to be made: batches for Python are bounded by their number of rows alone. Spark adds up a batch's bytes at every row otherwise,
        which for narrow rows takes longer than writing them."""
        conf, key = self.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
        before = conf.get(key)
        conf.set(key, str((1 << 31) - 1))
        try:
            yield
        finally:
            conf.set(key, before)

    def pack(self, halo: int | None, length: int = 1 << 20, width: int = 1) -> DataFrame:
        """The blocks that system.pack makes of ``tod()``, by ``width`` tasks or more."""
        most, all_ = self.rows.groupBy("interval_id").count().agg(F.max("count"), F.sum("count")).first()
        if (most or 0) > LONGEST:
            return pack(self.tod(), halo, length, width)
        buckets, place = max(width, -(-(all_ or 0) // DEALT)), self.place
        names = ["kinds", *(f"c{i}" for i in range(len(self.rows.columns)))]

        def deal(batches):
            held: list = []
            for b in batches:
                held.append(b)
                if sum(x.num_rows for x in held) >= SENT:
                    yield _sent(held, buckets, names)
                    held = []
            if any(x.num_rows for x in held):
                yield _sent(held, buckets, names)

        def run(batches):
            held, now = [], None
            for b in batches:
                for bucket, *row in zip(*b.columns):
                    if held and bucket.as_py() != now:
                        yield _blocks(_columns(held), place, halo, length)
                        held = []
                    now = bucket.as_py()
                    held.append(row)
            if held:
                yield _blocks(_columns(held), place, halo, length)

        sent = self.rows.mapInArrow(deal, ", ".join(["bucket int", *(f"{n} binary" for n in names)]))
        return sent.repartitionById(buckets, "bucket").coalesce(max(width, -(-buckets // ASIDE))).mapInArrow(run, BLOCK)


def _sent(held: list, buckets: int, names: list[str]) -> pa.RecordBatch:
    """A row for each bucket that gets samples: their columns as bytes, integers in four where they fit."""
    columns = []
    for i, c in enumerate(pa.Table.from_batches(held).combine_chunks().columns):
        if c.null_count and i < 2:
            raise ValueError(f"{c.null_count} samples have no interval or no {held[0].schema.names[1]}")
        whole = pa.types.is_integer(c.type)
        v = (c.cast(pa.int64()).fill_null(np.iinfo(np.int64).min) if whole and c.null_count else c).to_numpy()
        columns.append(v.astype(np.int32) if whole and -(1 << 31) <= v.min() and v.max() < 1 << 31 else v.astype(np.int64 if whole else float))
    to = (((columns[0].astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)) % np.uint64(buckets)).astype(np.uint16 if buckets <= 1 << 16 else np.uint32)
    order = np.argsort(to, kind="stable")
    ends = np.searchsorted(to[order], np.arange(buckets + 1))
    ends = np.append(ends[:-1][np.diff(ends) > 0], ends[-1])  # of buckets that get some
    whose = to[order[ends[:-1]]].astype(np.int32)
    kinds = np.array([v.itemsize + 8 * (v.dtype.kind == "f") for v in columns], np.uint8).tobytes()
    body = [pa.Array.from_buffers(pa.binary(), len(whose), [None, pa.py_buffer((ends * v.itemsize).astype(np.int32)), pa.py_buffer(v[order])]) for v in columns]
    return pa.record_batch([pa.array(whose), pa.array([kinds] * len(whose), pa.binary()), *body], names=["bucket", *names])


def _columns(held: list) -> list[np.ndarray]:
    """The columns of all samples that were sent to a task."""
    types = {4: np.int32, 8: np.int64, 16: np.float64}
    return [np.concatenate([np.frombuffer(row[1 + i].as_buffer(), types[row[0].as_py()[i]]) for row in held]) for i in range(len(held[0]) - 1)]


def arranged(columns: list[np.ndarray]) -> np.ndarray:
    """An order by all columns: by the first two at once where they fit one number, then what these leave open by the others."""
    a, b = (v.astype(np.int64) for v in columns[:2])
    low, span = int(b.min()), int(b.max()) - int(b.min()) + 1
    if (int(a.max()) - int(a.min()) + 1) * span >= 1 << 62:
        return np.lexsort(columns[::-1])
    key = (a - a.min()) * span + (b - low)
    order = np.argsort(key)
    same = np.diff(key[order]) == 0
    open_ = np.flatnonzero(np.append(same, False) | np.append(False, same))
    some = order[open_]
    order[open_] = some[np.lexsort([*(v[some] for v in columns[:1:-1]), key[some]])]
    return order


def _blocks(columns: list[np.ndarray], place: Callable, halo: int | None, length: int) -> pa.RecordBatch:
    order = arranged(columns)
    columns = [v[order] for v in columns]
    pix, phi, d, noise = place(columns[0].astype(np.int64), columns[1:])
    first = np.flatnonzero(np.diff(columns[0], prepend=columns[0][0] - 1))
    out: list = []
    for lo, hi in zip(first.tolist(), [*first[1:].tolist(), len(pix)]):
        n = hi - lo
        for chunk in range(1 if halo is None else -(-n // length)):
            start, end = (0, n) if halo is None else (max(0, chunk * length - halo), min(n, (chunk + 1) * length + halo))
            core = (0, n) if halo is None else (chunk * length - start, min(n, (chunk + 1) * length) - start)
            at = slice(lo + start, lo + end)
            u, local = np.unique(pix[at], return_inverse=True)
            out.append((int(columns[0][lo]), chunk, start, *core, int(noise[lo]), u, local.astype(np.int32), phi[at], d[at]))
    return block_batch(out)
