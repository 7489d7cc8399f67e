"""Packed sample blocks and the normal system, applied right to left and never formed."""

from __future__ import annotations

import copy
import functools
import zlib
from contextlib import nullcontext

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from skyweave.functions.kernels import Stationary
from skyweave.plans import strategy
from skyweave.sources.tables import require_columns

BLOCK = "interval_id long, chunk long, t0 long, core_lo int, core_hi int, noise_id int, upix array<long>, lpix array<int>, phi array<double>, d array<double>"
#: Bytes of all partial maps of a product that may be summed on the driver.
SMALL = 32 << 20
#: Columns of a block that are weighted together.
COLUMNS = 32
#: Samples of blocks that a product weights together; longer blocks stand alone.
TOGETHER = 1 << 16
#: Grouped blocks that a product weights at once, so that their transforms stay in a core's cache.
ASIDE = 16
#: Samples of a block up to which its part of a formed matrix is a product of all its modes, not made column by column.
DIRECT = 1024
#: Intervals whose hits are multiplied at once.
HITS = 512
#: Columns of a dense coarse space beyond which its image is taken by a formed matrix.
WIDE = 256
_NAMES = ["interval_id", "chunk", "t0", "core_lo", "core_hi", "noise_id", "upix", "lpix", "phi", "d"]


def pack(tod: DataFrame, halo: int | None, length: int = 1 << 20, width: int | None = None) -> DataFrame:
    """One row per chunk of an interval: its samples in time order with ``halo`` more on both sides (exact for a band no wider).

    t must be gapless within an interval; a slot without pointing (pix < 0, as pixel_cut leaves it) keeps its place in time, sees no pixel and has no data.
    halo None keeps intervals whole. Groups hold at most length + 2 * halo samples. ``width``: tasks that make them, at most (for blocks much fewer than an exchange's partitions)."""
    require_columns(tod, "interval_id", "t", "pix", "phi", "d", "noise_id")
    if halo is None:
        each = tod.withColumn("chunk", F.lit(0).cast("long"))
    else:
        at = lambda x: F.floor(x / length)
        each = tod.withColumn("chunk", F.explode(F.sequence(F.greatest(at(F.col("t") - halo), F.lit(0).cast("long")), at(F.col("t") + halo))))
    rows = each.groupBy("interval_id", "chunk").agg(F.first("noise_id").alias("noise_id"), F.collect_list(F.struct("t", "pix", "phi", "d")).alias("s"))

    def run(batches):
        for b in batches:
            out = []
            for k in range(b.num_rows):
                interval, chunk, noise = (b.column(i)[k].as_py() for i in range(3))
                t, pix, phi, d = (c.to_numpy(zero_copy_only=False) for c in b.column(3)[k].values.flatten())
                if (t[1:] < t[:-1]).any():  # mostly they come in order, and sorting here spares a sort of every row
                    order = np.argsort(t, kind="stable")
                    t, pix, phi, d = t[order], pix[order], phi[order], d[order]
                lo, hi = (0, len(t)) if halo is None else np.searchsorted(t, (chunk * length, (chunk + 1) * length)).tolist()
                if lo >= hi:
                    continue  # only a halo
                if t[-1] - t[0] != len(t) - 1:
                    raise ValueError(f"interval {interval} has gaps or repeats in t; use fill_gaps() or reindex()")
                blind = pix < 0
                u, l = np.unique(pix[~blind], return_inverse=True)
                if not len(u):
                    continue
                local = np.zeros(len(pix), np.int32)
                local[~blind] = l
                angle = np.where(blind, np.inf, np.nan_to_num(phi.astype(float)))  # marks the slot
                out.append((interval, chunk, int(t[0]), lo, hi, noise, u, local, angle, np.where(blind, 0.0, d.astype(float))))
            yield block_batch(out)

    return (rows.coalesce(width) if width else rows).mapInArrow(run, BLOCK)


def block_batch(rows: list[tuple]) -> pa.RecordBatch:
    """Rows of blocks, whose lists are arrays."""
    whole = [pa.array([r[i] for r in rows], pa.int64() if i < 3 else pa.int32()) for i in range(6)]
    lists = []
    for i, t in zip(range(6, 10), (np.int64, np.int32, float, float)):
        some = [r[i] for r in rows]
        ends = np.cumsum([0, *map(len, some)]).astype(np.int32)
        lists.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(some).astype(t, copy=False) if some else np.empty(0, t))))
    return pa.record_batch([*whole, *lists], names=_NAMES)


def save(blocks: DataFrame, path: str, buckets: int = 64) -> None:
    blocks.withColumn("bucket", F.pmod("interval_id", F.lit(buckets)).cast("int")).write.partitionBy("bucket").parquet(path)


def load(spark, path: str, intervals: int | None = None) -> DataFrame:
    b = spark.read.parquet(path)
    return (b if intervals is None else b.where(F.col("interval_id") < intervals)).drop("bucket")


def response(phi: np.ndarray, nstokes: int) -> np.ndarray:
    """Rows of P without their pixel; zero at slots without pointing."""
    seen = np.isfinite(phi)
    a = np.where(seen, phi, 0.0)
    return seen[None, :].astype(float) if nstokes == 1 else np.stack((np.ones_like(a), np.cos(2 * a), np.sin(2 * a))) * seen


def core_pixels() -> Column:
    """Pixels of the samples of a block's own part."""
    return F.expr("transform(filter(sequence(core_lo, core_hi - 1), i -> phi[i] < double('Infinity')), i -> upix[lpix[i]])")


def _distinct(batches):
    """The distinct pixels of a task's lists."""
    all_ = np.empty(0, np.int64)
    for b in batches:
        all_ = np.union1d(all_, b.column(0).flatten().to_numpy())
    yield pa.record_batch([pa.array(all_, pa.int64())], names=["pix"])


def _list(b, i, k):
    return b.column(i)[k].values.to_numpy(zero_copy_only=False)


def _rows(rows):
    """Batches (k, bytes of a row of doubles); rows of zeros are left out."""
    some: list = []
    for k, v in rows:
        if v.any():
            some.append((k, v.tobytes()))
        if len(some) == 64:
            yield pa.record_batch([pa.array([x[0] for x in some], pa.int32()), pa.array([x[1] for x in some], pa.binary())], names=["k", "v"])
            some = []
    if some:
        yield pa.record_batch([pa.array([x[0] for x in some], pa.int32()), pa.array([x[1] for x in some], pa.binary())], names=["k", "v"])


#: Bytes of a band of rows of a matrix that a task makes.
BAND = 16 << 20
#: Bytes of rows of a matrix that a task gets at once, besides those that it has.
BATCH = 4 << 20
#: Bytes of a matrix that a task may hold. Beyond them neither its bands nor its solution are begun, as they would write more than the matrix to disk before they failed.
ROOM = 8 << 30

GROUP = "noise_id int, size int, at binary, lo binary, hi binary, phi binary, ids binary, d binary"


def _grouped(pixels, nstokes: int, padded: bool):
    """Blocks of one noise id and about one length, side by side: numbers of pixels from 1 (0 where there is none; two bytes each if they fit), core ranges, angles, intervals and data, as bytes.
    ``padded``: zeros after a block's end don't change its weighting; else only equal lengths meet."""

    def run(batches):
        held: dict = {}
        number = np.uint16 if len(pixels.value) < 1 << 16 else np.int32

        def row(key):
            noise, size = key
            some = held.pop(key)
            at, phi, d = np.zeros((len(some), size), number), np.zeros((len(some), size if nstokes > 1 else 0)), np.zeros((len(some), size))
            for j, (_, _, a, f, _, x) in enumerate(some):
                at[j, : len(a)], d[j, : len(a)] = a, x
                if nstokes > 1:
                    phi[j, : len(a)] = f
            body = (at, np.array([x[0] for x in some], np.int32), np.array([x[1] for x in some], np.int32), phi, np.array([x[4] for x in some], np.int64), d)
            return pa.record_batch([pa.array([noise], pa.int32()), pa.array([size], pa.int32()), *(pa.array([x.tobytes()], pa.binary()) for x in body)], names=["noise_id", "size", "at", "lo", "hi", "phi", "ids", "d"])

        for b in batches:
            for k in range(b.num_rows):
                interval, lo, hi, noise = (b.column(i)[k].as_py() for i in (0, 3, 4, 5))
                phi = _list(b, 8, k)
                at = np.where(np.isfinite(phi), np.searchsorted(pixels.value, _list(b, 6, k))[_list(b, 7, k)] + 1, 0)
                n = len(at)
                step = max(1, 1 << max(0, n.bit_length() - 4)) if padded else 1
                key = (noise, -(-n // step) * step)
                held.setdefault(key, []).append((lo, hi, at, np.where(np.isfinite(phi), phi, 0.0), interval, _list(b, 9, k)))
                if len(held[key]) * key[1] >= TOGETHER:
                    yield row(key)
                elif sum(len(v) * key[1] for key, v in held.items()) > 16 * TOGETHER:
                    yield row(max(held, key=lambda key: len(held[key]) * key[1]))
        for key in list(held):
            yield row(key)

    return run


def _groups(batches):
    """(noise id, pixel numbers plus 1, the same in cores and 0 elsewhere, angles or None, data) of grouped blocks, each (blocks, samples). Data are None where their column was left out."""
    for b in batches:
        for k in range(b.num_rows):
            noise, size = b.column(0)[k].as_py(), b.column(1)[k].as_py()
            body = [c[k].as_buffer() for c in b.columns[2:]]
            lo, hi = np.frombuffer(body[1], np.int32), np.frombuffer(body[2], np.int32)
            at = np.frombuffer(body[0], np.uint16 if body[0].size == 2 * size * len(lo) else np.int32).reshape(-1, size)
            i = np.arange(size, dtype=np.int32)
            last = int(hi.min())
            out = at if not lo.any() and not at[:, last:][i[last:] >= hi[:, None]].any() else np.where((i >= lo[:, None]) & (i < hi[:, None]), at, 0)
            phi = np.frombuffer(body[3]).reshape(len(at), -1)
            yield noise, at, out, phi if phi.size else None, np.frombuffer(body[5]).reshape(-1, size) if len(body) > 5 else None


def _intervals(batches):
    """The intervals of grouped blocks."""
    for b in batches:
        yield pa.record_batch([pa.array(np.unique(np.concatenate([np.empty(0, np.int64), *(np.frombuffer(x.as_buffer(), np.int64) for x in b.column(0))])))], names=["interval_id"])


def _hit_blocks(batches, n: int):
    """(interval, numbers of the pixels that its core sees, how often) of every block of grouped blocks."""
    for b in batches:
        ids = [np.frombuffer(x, np.int64) for x in b.column(6).to_pylist()]
        for (_, _, out, _, _), own in zip(_groups([b]), ids):
            for interval, cells in zip(own.tolist(), out):
                h = np.bincount(cells, minlength=n + 1)[1:]
                at = np.flatnonzero(h)
                yield interval, at, h[at]


def _angles(at: np.ndarray, phi: np.ndarray | None, nstokes: int) -> list:
    """Rows of P without their pixel, for grouped blocks; slots without a pixel are left to their number."""
    return [1.0] if nstokes == 1 else [1.0, np.cos(2 * phi), np.sin(2 * phi)]


class NormalOperator:
    """P' W P over packed blocks, with vectors on the driver (their size is checked; see DistributedOperator for more).

    Each product is one job: the vectors are broadcast, every task gathers, weights and sums all its blocks into one partial map,
    and partial maps are summed by pixel in one shuffle."""

    def __init__(self, tod: DataFrame, model, nstokes: int = 1, length: int = 1 << 20, budget: int = strategy.BROADCAST_BUDGET, rank: int = 0, tasks: int | None = None):
        """``tod`` may be ``arrange.Unplaced``. ``rank`` columns of a coarse space are counted into the size of the vectors; ``tasks`` fixes how many work on a product."""
        self.spark, self.model, self.s = tod.sparkSession, model, nstokes
        width = 4 * self.spark.sparkContext.defaultParallelism
        with nullcontext() if isinstance(tod, DataFrame) else tod.planned():
            packed = pack(tod, model.halo, length, width) if isinstance(tod, DataFrame) else tod.pack(model.halo, length, width)
            self.blocks = (packed.repartition(tasks, "interval_id", "chunk") if tasks else packed).persist(StorageLevel.MEMORY_AND_DISK)
            seen = self.blocks.select("upix").mapInArrow(_distinct, "pix long").distinct().toArrow().column("pix").to_numpy()
        # a product has as many tasks as run at once: each adds up all its blocks before it sends, so more of them send more partial maps and start for nothing
        self.work = self.blocks.coalesce(tasks or self.spark.sparkContext.defaultParallelism)
        self.tasks = self.work.rdd.getNumPartitions()
        self.plan = strategy.choose(len(seen), nstokes, rank, budget)
        if self.plan.kind != "broadcast":
            raise ValueError(f"{self.plan.explain()}: use DistributedOperator")
        self.pixels = np.sort(seen)
        self._group()
        self.n = len(self.pixels) * nstokes
        self.products = 0
        self.a: np.ndarray | None = None
        self.bands: Bands | None = None
        self._known: dict = {}  # intervals and hits

    def _group(self) -> None:
        """Blocks side by side, for products: made once, as bytes."""
        made = _grouped(self.spark.sparkContext.broadcast(self.pixels), self.s, self.model.halo is not None)
        self.groups = self.work.mapInArrow(made, GROUP).persist(StorageLevel.MEMORY_AND_DISK_DESER)  # a product reads no bytes of columns that it leaves out

    def other(self, model) -> "NormalOperator":
        """The operator of another noise model on the same blocks, whose halo is exact for any band no wider. Closing one closes both."""
        if self.model.halo is None or model.halo is None or model.halo > self.model.halo:
            raise ValueError(f"blocks with a halo of {self.model.halo} don't serve a band of {model.halo}")
        op = copy.copy(self)
        op.model, op.products, op.a, op.bands = model, 0, None, None
        return op

    def dealt(self, tasks: int) -> "NormalOperator":
        """The same system with its blocks dealt to so many tasks, to be closed by itself."""
        op = copy.copy(self)
        op.blocks = self.blocks.repartition(tasks, "interval_id", "chunk").persist(StorageLevel.MEMORY_AND_DISK)
        op.work, op.tasks, op.products, op.a, op.bands, op._known = op.blocks, tasks, 0, None, None, {}
        op._group()
        return op

    def form(self, budget: int = strategy.BROADCAST_BUDGET) -> "NormalOperator":
        """Form the system matrix in one pass over the samples if it fits ``budget`` bytes; products are then taken on the driver. For many solves of one small system:
        the pass costs a weighting of the pixels that each block sees. Where it does not fit, products stay passes over the blocks."""
        if self.a is None and self.n * self.n * 8 <= budget:
            self.a = self._formed()
        return self

    def _formed(self) -> np.ndarray:
        s, model, n = self.s, self.model, self.n

        def run(batches):
            total, scales = None, {}
            for noise, at, out, phi, _ in _groups(batches):
                if total is None:
                    total = np.zeros((n, n))
                size, r = at.shape[1], _angles(at, phi, s)
                for k in range(len(at)):
                    own = np.flatnonzero(at[k])
                    core = out[k, own] > 0
                    if not core.any():
                        continue
                    pixels, local = np.unique(at[k, own].astype(int) - 1, return_inverse=True)
                    cells = (pixels[:, None] * s + np.arange(s)).ravel()
                    if model.halo is not None and size <= DIRECT:
                        # the weights are diagonal in the modes of the block with its zeros: a product of the modes of what the pixels see
                        m, v = model.spectrum(noise, size)
                        y = np.zeros((len(pixels), s, m))
                        for i in range(s):
                            y[local, i, own] = r[i][k, own] if i else 1.0
                        modes = np.fft.rfft(y.reshape(-1, m)).view(float)
                        if (noise, m) not in scales:
                            both = np.full(len(v), 2.0 / m)  # a mode and its conjugate, but for the mean and the last of an even length
                            both[0] = 1.0 / m
                            if m % 2 == 0:
                                both[-1] = 1.0 / m
                            scales[noise, m] = np.repeat(v * both, 2), np.repeat(np.sqrt(np.abs(v) * both), 2), v.min() >= 0
                        scale, root, positive = scales[noise, m]
                        if core.all() and positive:
                            modes *= root
                            total[np.ix_(cells, cells)] += modes @ modes.T  # half the work, as it is symmetric
                            continue
                        within = modes
                        if not core.all():
                            y[local[~core], :, own[~core]] = 0.0
                            within = np.fft.rfft(y.reshape(-1, m)).view(float)
                        total[np.ix_(cells, cells)] += (modes * scale) @ within.T
                        continue
                    by_pixel, order = np.argsort(local, kind="stable"), np.argsort(local[core], kind="stable")
                    ends, to = np.searchsorted(local[by_pixel], np.arange(len(pixels) + 1)), own[core][order]
                    seen, starts = np.unique(local[core][order], return_index=True)
                    for first in range(0, len(pixels), COLUMNS):
                        last = min(first + COLUMNS, len(pixels))
                        mine = by_pixel[ends[first] : ends[last]]
                        for i in range(s):
                            y = np.zeros((last - first, size))
                            y[local[mine] - first, own[mine]] = r[i][k, own[mine]] if i else 1.0
                            z = model.weight(noise, y)[:, to]
                            for j in range(s):
                                total[np.ix_(pixels[first:last] * s + i, pixels[seen] * s + j)] += np.add.reduceat(z * r[j][k, to] if j else z, starts, axis=1)
            if total is not None:
                yield from _rows((k, total[k, k:]) for k in range(n))

        def add(batches):
            out: dict[int, np.ndarray] = {}
            for b in batches:
                for k, v in zip(b.column(0).to_pylist(), b.column(1)):
                    part = np.frombuffer(v.as_buffer())
                    if k in out:
                        out[k] += part
                    else:
                        out[k] = part.copy()
            yield from _rows(out.items())

        parts = self.groups.drop("d").mapInArrow(run, "k int, v binary")
        got = parts.repartition(self.tasks, "k").mapInArrow(add, "k int, v binary").toArrow()
        a = np.zeros((n, n))
        for k, v in zip(got.column("k").to_pylist(), got.column("v")):
            a[k, k:] = np.frombuffer(v.as_buffer())  # it is symmetric
        for lo in range(0, n, 512):
            a[lo:, lo : lo + 512] = np.where(np.arange(lo, n)[:, None] > np.arange(lo, min(lo + 512, n)), a[lo : lo + 512, lo:].T, a[lo:, lo : lo + 512])
        return a

    def banded(self) -> "Bands":
        """The system matrix in bands of rows that tasks keep, for one that is not for the driver."""
        if self.n * self.n * 8 > ROOM:
            raise ValueError(f"a matrix of {self.n} unknowns has {self.n * self.n * 8} bytes, more than the {ROOM} that a task may hold; take an iterative solver")
        if self.bands is None:
            self.bands = Bands(self)
        return self.bands

    def _summed(self, run, size: int, of: DataFrame | None = None) -> np.ndarray:
        """Sum of the tasks' partial maps: by pixel in a shuffle, or on the driver where all of them together are small."""
        parts = (self.work if of is None else of).mapInArrow(run, "k long, v double")
        if self.tasks * size * 16 > SMALL:
            parts = parts.groupBy("k").agg(F.sum("v").alias("v"))
        got = parts.toArrow()
        return np.bincount(got.column("k").to_numpy(), got.column("v").to_numpy(), size)

    def _run(self, columns: np.ndarray | None, sparse: bool = False) -> np.ndarray:
        """(n, r) -> (n, r); None stands for the data stream."""
        s, model, width = self.s, self.model, 1 if columns is None else columns.shape[1]
        n = len(self.pixels)
        if width == 1 or not sparse:
            return self._dense(columns)
        shared = self.spark.sparkContext.broadcast((self.pixels, columns.reshape(n, s, width)))

        def run(batches):
            pixels, x = shared.value
            total: dict[int, np.ndarray] = {}  # of the columns that the task's blocks touch
            for b in batches:
                for k in range(b.num_rows):
                    lo, hi, noise = (b.column(i)[k].as_py() for i in (3, 4, 5))
                    at = np.searchsorted(pixels, _list(b, 6, k))
                    local, r = _list(b, 7, k), response(_list(b, 8, k), s)
                    own = x[at]
                    cols = np.flatnonzero(np.abs(own).sum(axis=(0, 1)))  # only columns that are not zero on this block's pixels
                    where = at[local[lo:hi]]
                    for first in range(0, len(cols), COLUMNS):
                        some = cols[first : first + COLUMNS]
                        z = model.weight(noise, np.einsum("sn,nsr->rn", r, own[:, :, some][local]))[:, lo:hi]
                        for j, c in enumerate(some.tolist()):
                            if c not in total:
                                total[c] = np.zeros(n * s)
                            for i in range(s):
                                total[c][i::s] += np.bincount(where, z[j] * r[i, lo:hi], n)
            for c, v in total.items():
                hit = np.flatnonzero(v)
                yield pa.record_batch([pa.array(hit * width + c, pa.int64()), pa.array(v[hit])], names=["k", "v"])

        out = self._summed(run, n * s * width)
        shared.destroy()
        self.products += width
        return out.reshape(n * s, width)

    def _dense(self, columns: np.ndarray | None) -> np.ndarray:
        """The product with columns of which blocks see most, or with the data stream, by grouped blocks."""
        s, model, n, width = self.s, self.model, len(self.pixels), 1 if columns is None else columns.shape[1]
        x = None if columns is None else np.concatenate((np.zeros((width, s, 1)), columns.reshape(n, s, width).transpose(2, 1, 0)), axis=2)  # what sees no pixel has number 0
        shared = self.spark.sparkContext.broadcast(x)

        def run(batches):
            x, total = shared.value, np.zeros((width, s, n + 1))
            for noise, at, out, phi, d in _groups(batches):
                r = _angles(at, phi, s)
                for first in range(0, len(at), ASIDE):
                    some = slice(first, first + ASIDE)
                    cells, to = at[some].astype(int), out[some].astype(int).ravel()
                    for c in range(width):
                        y = d[some] if x is None else sum(x[c, i].take(cells) * r[i][some] if i else x[c, 0].take(cells) for i in range(s))
                        z = model.weight(noise, y)
                        for i in range(s):
                            total[c, i] += np.bincount(to, (z * r[i][some] if i else z).ravel(), n + 1)
            flat = total[:, :, 1:].transpose(2, 1, 0).ravel()
            hit = np.flatnonzero(flat)
            yield pa.record_batch([pa.array(hit, pa.int64()), pa.array(flat[hit])], names=["k", "v"])

        out = self._summed(run, n * s * width, self.groups if x is None else self.groups.drop("ids", "d"))
        shared.destroy()
        self.products += width
        return out.reshape(n * s, width)

    def apply(self, x: np.ndarray) -> np.ndarray:
        return self.apply_many(x.reshape(-1, 1))[:, 0]

    def apply_many(self, x: np.ndarray, sparse: bool = False) -> np.ndarray:
        """All columns in one pass over the blocks, or by the matrix if it was formed."""
        if self.a is None:
            return self._run(x, sparse)
        self.products += x.shape[1]
        return self.a @ x

    def image(self, z: np.ndarray, sparse: bool = False) -> np.ndarray:
        """A Z: for columns of which most blocks would see most, by a matrix that is formed for this alone, which weights a block's own pixels only."""
        if self.a is None and z.shape[1] > WIDE and (z != 0).mean() > 0.5 and self.n * self.n * 8 <= strategy.BROADCAST_BUDGET:
            return self._formed() @ z
        return self.apply_many(z, sparse)

    def rhs(self) -> np.ndarray:
        return self._run(None)[:, 0]

    def diagonal_blocks(self) -> np.ndarray:
        """(n_pix, s, s) blocks of P' diag(W) P."""
        s, model, n = self.s, self.model, len(self.pixels)

        def run(batches):
            total = np.zeros((s, s, n + 1))
            for noise, at, out, phi, _ in _groups(batches):
                r, w0 = _angles(at, phi, s), model.diag(noise)
                for i in range(s):
                    for j in range(s):
                        total[i, j] += w0 * np.bincount(out.ravel(), None if s == 1 else np.broadcast_to(r[i] * r[j], out.shape).ravel(), n + 1)
            flat = total[:, :, 1:].transpose(2, 0, 1).ravel()
            hit = np.flatnonzero(flat)
            yield pa.record_batch([pa.array(hit, pa.int64()), pa.array(flat[hit])], names=["k", "v"])

        return self._summed(run, n * s * s, self.groups.drop("d")).reshape(-1, s, s)

    def weighting_seconds(self) -> float:
        """Seconds of noise weighting in one product, over all tasks."""
        model = self.model

        def run(batches):
            import time

            for noise, _, _, _, d in _groups(batches):
                t = time.perf_counter()
                model.weight(noise, d)
                yield pa.record_batch([pa.array([time.perf_counter() - t])], names=["s"])

        return self.groups.mapInArrow(run, "s double").agg(F.sum("s")).first()[0] or 0.0

    def intervals(self) -> np.ndarray:
        if "intervals" not in self._known:
            ids = self.groups.select("ids").mapInArrow(_intervals, "interval_id long").toArrow().column("interval_id").to_numpy()
            self._known["intervals"] = np.unique(ids)
        return self._known["intervals"]

    def _hit_rows(self) -> DataFrame:
        """(interval_id, at, n): by block, the numbers of the pixels that it sees in its core and how often."""
        n = len(self.pixels)

        def run(batches):
            for b in batches:
                out = list(zip(*_hit_blocks([b], n))) or [[], [], []]
                yield pa.record_batch([pa.array(out[0], pa.int64()), pa.array(out[1], pa.list_(pa.int32())), pa.array(out[2], pa.list_(pa.int64()))], names=["interval_id", "at", "n"])

        return self.groups.drop("d").mapInArrow(run, "interval_id long, at array<int>, n array<long>")

    def hits_merged(self, rank: int) -> np.ndarray:
        """(n_pix, rank) hits of ``rank`` runs of intervals, as merge_columns deals them; no more than that is on the driver."""
        n, ids = len(self.pixels), self.spark.sparkContext.broadcast(self.intervals())

        def run(batches):
            total: dict[int, np.ndarray] = {}
            for interval, at, some in _hit_blocks(batches, n):
                c = int(np.searchsorted(ids.value, interval)) * rank // len(ids.value)
                if c not in total:
                    total[c] = np.zeros(n)
                total[c][at] += some
            for c, v in total.items():
                hit = np.flatnonzero(v)
                yield pa.record_batch([pa.array(hit * rank + c, pa.int64()), pa.array(v[hit])], names=["k", "v"])

        return self._summed(run, n * rank, self.groups.drop("d")).reshape(n, rank)

    def hits_gram(self) -> np.ndarray:
        """H H' for the (n_pix, K) hits H, some intervals at a time: what the span of H's columns needs, whatever their number."""
        n = len(self.pixels)

        def run(batches):
            total, h, at, last = np.zeros((n, n)), np.zeros((n, HITS)), -1, None
            for b in batches:
                for k in range(b.num_rows):
                    if (i := b.column(0)[k].as_py()) != last:
                        last, at = i, at + 1
                        if at == HITS:
                            total += h @ h.T
                            h[:], at = 0.0, 0
                    h[_list(b, 1, k), at] += _list(b, 2, k)
            total += h @ h.T
            yield from _rows(enumerate(total))

        def add(batches):
            out: dict[int, np.ndarray] = {}
            for b in batches:
                for k, v in zip(b.column(0).to_pylist(), b.column(1)):
                    out[k] = out.get(k, 0.0) + np.frombuffer(v.as_buffer())
            yield from _rows(out.items())

        parts = self._hit_rows().repartition(self.tasks, "interval_id").sortWithinPartitions("interval_id").mapInArrow(run, "k int, v binary")
        got = parts.repartition(self.tasks, "k").mapInArrow(add, "k int, v binary").toArrow()
        a = np.zeros((n, n))
        for k, v in zip(got.column("k").to_pylist(), got.column("v")):
            a[k] = np.frombuffer(v.as_buffer())
        return a

    def hits(self) -> tuple[np.ndarray, np.ndarray]:
        """(interval ids, (n_pix, K) hits)."""
        if "hits" not in self._known:
            got = self._hit_rows().toArrow().combine_chunks()
            interval, col = np.unique(got.column("interval_id").to_numpy(), return_inverse=True)
            h = np.zeros((len(self.pixels), len(interval)))
            for k, c in enumerate(col.tolist()):
                h[got.column("at")[k].values.to_numpy(), c] += got.column("n")[k].values.to_numpy()
            self._known["hits"] = interval, h
        return self._known["hits"]

    def table(self, x: np.ndarray) -> DataFrame:
        """A vector as a wide map."""
        v = x.reshape(len(self.pixels), self.s)
        names = ["i"] if self.s == 1 else ["i", "q", "u"]
        return self.spark.createDataFrame(pa.table({"pix": pa.array(self.pixels), **{n: pa.array(v[:, k].copy()) for k, n in enumerate(names)}}))

    def close(self) -> None:
        if self.bands is not None:
            self.bands.rows.unpersist()
        self.groups.unpersist()
        self.blocks.unpersist()


def _add_lags(total: np.ndarray, first: int, w: np.ndarray, at: np.ndarray, out: np.ndarray, r: list) -> None:
    """Add to the rows of a band of pixels, the first of which has number ``first``, what their samples in cores see within the band of w. ``total``: (pixels, s, pixels of all plus 1, s)."""
    mine, size = (out > first) & (out <= first + len(total)), at.shape[1]
    block, t = np.nonzero(mine)
    reach, s = min(len(w), size) - 1, len(r)
    lags = np.arange(-reach, reach + 1)
    both, step, flat = w[np.abs(lags)], max(1, (1 << 20) // len(lags)), total.reshape(-1)
    for lo in range(0, len(t), step):
        k, here = block[lo : lo + step, None], t[lo : lo + step, None]
        near = here + lags
        inside = (near >= 0) & (near < size)
        near = np.where(inside, near, 0)
        number = np.where(inside, at[k, near], 0).astype(np.int64)
        row = out[k, here].astype(np.int64) - 1 - first
        for i in range(s):
            for j in range(s):
                v = np.broadcast_to(both, number.shape)
                if i:
                    v = v * r[i][k, here]
                if j:
                    v = v * r[j][k, near]
                np.add.at(flat, (((row * s + i) * total.shape[2] + number) * s + j).ravel(), v.ravel())


def _add_columns(total: np.ndarray, first: int, model, noise: int, at: np.ndarray, out: np.ndarray, r: list) -> None:
    """The same for weights of any kind: by weighting what each pixel of the band sees of a block."""
    s, size = len(r), at.shape[1]
    for k in range(len(at)):
        mine = np.flatnonzero((at[k] > first) & (at[k] <= first + len(total)))
        pixels, local = np.unique(at[k, mine].astype(np.int64) - 1 - first, return_inverse=True)
        for lo in range(0, len(pixels), COLUMNS):
            some = (local >= lo) & (local < lo + COLUMNS)
            for i in range(s):
                y = np.zeros((min(COLUMNS, len(pixels) - lo), size))
                y[local[some] - lo, mine[some]] = r[i][k, mine[some]] if i else 1.0
                z = model.weight(noise, y)
                for j in range(s):
                    for p, v in zip(pixels[lo : lo + COLUMNS], z):
                        total[p, i, :, j] += np.bincount(out[k], v * r[j][k] if j else v, total.shape[2])


class Bands:
    """A system matrix that tasks make and keep, as the lower part of its rows (k, bytes of its cells). Products are the operator's passes over the blocks, as long as that is open;
    what needs all cells at once is a task's that has room for them."""

    __array_ufunc__ = None  # a product with an array from the left is __rmatmul__'s

    def __init__(self, op: NormalOperator):
        s, model, n = op.s, op.model, len(op.pixels)
        self.op, self.n, self.shape = op, op.n, (op.n, op.n)
        pixels = max(1, min(-(-n // op.tasks), BAND // (8 * s * op.n)))  # of a band
        count = -(-n // pixels)

        def run(batches):
            total, first = None, 0
            for b in batches:
                if total is None and b.num_rows:
                    first = b.column(0)[0].as_py() * pixels
                    total = np.zeros((min(pixels, n - first), s, n + 1, s))
                for noise, at, out, phi, _ in _groups([pa.record_batch(b.columns[1:], names=b.schema.names[1:])]):
                    if isinstance(model, Stationary):
                        _add_lags(total, first, model.kernels[noise], at, out, _angles(at, phi, s))
                    else:
                        _add_columns(total, first, model, noise, at, out, _angles(at, phi, s))
            if total is not None:
                yield from _rows((first * s + k, row[: (first + k // s + 1) * s]) for k, row in enumerate(total[:, :, 1:, :].reshape(-1, n * s)))

        each = op.groups.drop("ids", "d").select(F.explode(F.sequence(F.lit(0), F.lit(count - 1))).alias("band"), "noise_id", "size", "at", "lo", "hi", "phi")
        self.rows = each.repartitionById(count, "band").mapInArrow(run, "k int, v binary").persist(StorageLevel.MEMORY_AND_DISK)

    def __matmul__(self, x: np.ndarray) -> np.ndarray:
        return self.op.apply_many(x.reshape(self.n, -1)).reshape(x.shape)

    def __rmatmul__(self, x: np.ndarray) -> np.ndarray:
        return (self @ x.T).T  # it is symmetric

    def whole(self, works: list) -> list[np.ndarray]:
        """What each of ``works`` makes of the whole matrix, of which it gets the lower part (with the whole blocks of the diagonal) and may change it; each in a task of its own, all at once."""
        n = self.n

        def one(at: int, work):
            def run(batches):
                a = np.zeros((n, n))
                for b in batches:
                    for k, v in zip(b.column(0).to_pylist(), b.column(1)):
                        row = np.frombuffer(v.as_buffer())
                        a[k, : len(row)] = row
                yield pa.record_batch([pa.array([at], pa.int32()), pa.array([np.ascontiguousarray(work(a), float).tobytes()], pa.binary())], names=["at", "v"])

            return self.rows.coalesce(1).mapInArrow(run, "at int, v binary")

        self.rows.count()  # made by all tasks before single ones read them
        conf, key = self.op.spark.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
        before = conf.get(key)
        conf.set(key, str(BATCH))
        try:
            got = functools.reduce(DataFrame.unionAll, [one(at, work) for at, work in enumerate(works)]).toArrow()
        finally:
            conf.set(key, before)
        found = dict(zip(got.column("at").to_pylist(), got.column("v")))
        return [np.frombuffer(found[at].as_buffer()) for at in range(len(works))]


class DistributedOperator:
    """The same product with vectors as tables (pix, v0..): blocks meet the vector through their pixel lists."""

    def __init__(self, tod: DataFrame, model, nstokes: int = 1, length: int = 1 << 20):
        self.spark, self.model, self.s = tod.sparkSession, model, nstokes
        self.blocks = pack(tod, model.halo, length).persist(StorageLevel.MEMORY_AND_DISK)
        self.lists = self.blocks.select("interval_id", "chunk", F.posexplode("upix").alias("at", "pix"))
        self.names = [f"v{i}" for i in range(nstokes)]

    def _run(self, fed: DataFrame, data: bool) -> DataFrame:
        s, model, names = self.s, self.model, self.names

        def run(batches):
            for b in batches:
                out = [[] for _ in range(s + 1)]
                for k in range(b.num_rows):
                    lo, hi, noise = (b.column(i)[k].as_py() for i in (3, 4, 5))
                    u, local, r = _list(b, 6, k), _list(b, 7, k), response(_list(b, 8, k), s)
                    y = _list(b, 9, k) if data else sum(r[i] * _list(b, 10 + i, k)[local] for i in range(s))
                    z = model.weight(noise, y[None, :])[0, lo:hi]
                    out[0].append(u)
                    for i in range(s):
                        out[1 + i].append(np.bincount(local[lo:hi], z * r[i, lo:hi], len(u)))
                if out[0]:
                    yield pa.record_batch([pa.array(np.concatenate(c)) for c in out], names=["pix", *names])

        made = fed.mapInArrow(run, ", ".join(["pix long", *(f"{n} double" for n in names)]))
        return made.groupBy("pix").agg(*(F.sum(n).alias(n) for n in names))

    def apply(self, x: DataFrame) -> DataFrame:
        own = self.lists.join(x, "pix").groupBy("interval_id", "chunk").agg(F.sort_array(F.collect_list(F.struct("at", *self.names))).alias("x"))
        return self._run(self.blocks.join(own, ["interval_id", "chunk"]).select(*_NAMES, *(F.col(f"x.{n}").alias(f"x_{n}") for n in self.names)), False)

    def a_priori(self, rank: int) -> DataFrame:
        """(pix, col, z): a pixel's share of hits by interval, intervals dealt to ``rank`` columns; intensity rows alone are not zero."""
        hits = self.blocks.select((F.pmod("interval_id", F.lit(rank))).cast("int").alias("col"), F.explode(core_pixels()).alias("pix")).groupBy("pix", "col").agg(F.count("*").alias("n"))
        return hits.join(hits.groupBy("pix").agg(F.sum("n").alias("all")), "pix").select("pix", "col", (F.col("n") / F.col("all")).alias("z"))

    def diagonal_cells(self) -> DataFrame:
        """(pix, c0..): the cells of each pixel's block of P' diag(W) P, row by row."""
        s, model, names = self.s, self.model, [f"c{k}" for k in range(self.s * self.s)]

        def run(batches):
            for b in batches:
                for k in range(b.num_rows):
                    lo, hi, noise = (b.column(i)[k].as_py() for i in (3, 4, 5))
                    u, local, r = _list(b, 6, k), _list(b, 7, k)[lo:hi], response(_list(b, 8, k)[lo:hi], s)
                    cells = [model.diag(noise) * np.bincount(local, r[i] * r[j], len(u)) for i in range(s) for j in range(s)]
                    yield pa.record_batch([pa.array(u), *map(pa.array, cells)], names=["pix", *names])

        made = self.blocks.select(*_NAMES).mapInArrow(run, ", ".join(["pix long", *(f"{n} double" for n in names)]))
        return made.groupBy("pix").agg(*(F.sum(n).alias(n) for n in names))

    def apply_coarse(self, z: DataFrame) -> DataFrame:
        """A Z as (pix, col, v0..) for Z as (pix, col, z): every block gets the columns of its own pixels alone, some at a time."""
        s, model, names = self.s, self.model, self.names
        own = self.lists.join(z, "pix").groupBy("interval_id", "chunk").agg(F.collect_list(F.struct("at", "col", "z")).alias("x"))
        fed = self.blocks.join(own, ["interval_id", "chunk"]).select(*_NAMES, *(F.col(f"x.{n}").alias(f"x_{n}") for n in ("at", "col", "z")))

        def run(batches):
            for b in batches:
                for k in range(b.num_rows):
                    lo, hi, noise = (b.column(i)[k].as_py() for i in (3, 4, 5))
                    u, local, r = _list(b, 6, k), _list(b, 7, k), response(_list(b, 8, k), s)
                    at, col, v = (_list(b, i, k) for i in (10, 11, 12))
                    cols = np.unique(col)
                    for first in range(0, len(cols), COLUMNS):
                        some = cols[first : first + COLUMNS]
                        mine = np.isin(col, some)
                        x = np.zeros((len(some), len(u)))
                        x[np.searchsorted(some, col[mine]), at[mine]] = v[mine]
                        w = model.weight(noise, x[:, local] * r[0])[:, lo:hi]
                        for j, c in enumerate(some.tolist()):
                            out = [np.bincount(local[lo:hi], w[j] * r[i, lo:hi], len(u)) for i in range(s)]
                            yield pa.record_batch([pa.array(u), pa.array(np.full(len(u), c, np.int32)), *map(pa.array, out)], names=["pix", "col", *names])

        made = fed.mapInArrow(run, ", ".join(["pix long", "col int", *(f"{n} double" for n in names)]))
        return made.groupBy("pix", "col").agg(*(F.sum(n).alias(n) for n in names))

    def rhs(self) -> DataFrame:
        return self._run(self.blocks.select(*_NAMES), True)


def weight_lag_join(tod: DataFrame, kernels: DataFrame, value: str = "d") -> DataFrame:
    """(interval_id, t, y) = W d by an equi-join over lags; kernels is (noise_id, lag, w). N * (2 lambda + 1) rows: for reference."""
    k = kernels.groupBy("noise_id").agg(F.sort_array(F.collect_list(F.struct("lag", "w"))).alias("k"))
    src = tod.select("interval_id", "t", "noise_id", F.col(value).alias("v")).join(F.broadcast(k), "noise_id")  # one row per kernel
    each = src.select("interval_id", "t", "v", F.explode("k").alias("k"))
    both = each.select("interval_id", (F.col("t") + F.col("k.lag")).alias("t"), (F.col("v") * F.col("k.w")).alias("y")).unionByName(each.where("k.lag > 0").select("interval_id", (F.col("t") - F.col("k.lag")).alias("t"), (F.col("v") * F.col("k.w")).alias("y")))
    return both.groupBy("interval_id", "t").agg(F.sum("y").alias("y")).join(tod.select("interval_id", "t"), ["interval_id", "t"], "left_semi")


def weight_fir(tod: DataFrame, kernels: DataFrame, lambda_: int, value: str = "d") -> DataFrame:
    """The same by a moving frame of 2 lambda + 1 samples (for small bands): native functions only."""
    k = kernels.groupBy("noise_id").agg(F.sort_array(F.collect_list(F.struct("lag", "w"))).alias("k")).select("noise_id", F.col("k.w").alias("w"))
    frame = W.partitionBy("interval_id").orderBy("t").rowsBetween(-lambda_, lambda_)
    framed = tod.select("interval_id", "t", "noise_id", F.collect_list(F.struct(F.col("t").alias("t"), F.col(value).alias("v"))).over(frame).alias("near"))
    y = F.expr("aggregate(near, 0D, (a, x) -> a + x.v * element_at(w, cast(abs(x.t - t) + 1 as int)))")
    return framed.join(F.broadcast(k), "noise_id").select("interval_id", "t", y.alias("y"))


def weight_fft(tod: DataFrame, model, length: int = 1 << 20) -> DataFrame:
    """The same by zero-padded transforms over packed blocks."""
    def run(batches):
        for b in batches:
            for k in range(b.num_rows):
                interval, t0, lo, hi, noise = (b.column(i)[k].as_py() for i in (0, 2, 3, 4, 5))
                y = model.weight(noise, _list(b, 9, k)[None, :])[0, lo:hi]
                yield pa.record_batch([pa.array(np.full(hi - lo, interval, np.int64)), pa.array(t0 + np.arange(lo, hi)), pa.array(y)], names=["interval_id", "t", "y"])

    return pack(tod, model.halo, length).mapInArrow(run, "interval_id long, t long, y double")


def explicit(tod: DataFrame, kernels: DataFrame, lambda_: int, length: int = 1 << 14) -> DataFrame:
    """(p, q, v) cells of P' W P for intensity. Each block sends, by the lower pixel of a pair, the higher ones and the lags of its sample pairs at most ``lambda_``
    apart, sorted and packed to some bytes a pair, once for both orders: one exchange, in which no pair is a row. The cells themselves are the caller's to hold."""
    w: dict[int, np.ndarray] = {}
    for r in kernels.where(F.col("lag") <= lambda_).collect():  # a band for each noise id
        w.setdefault(r["noise_id"], np.zeros(lambda_ + 1))[r["lag"]] = r["w"]

    def run(batches):
        for b in batches:
            for k in range(b.num_rows):
                lo, hi, noise = (b.column(i)[k].as_py() for i in (3, 4, 5))
                u, local, seen = _list(b, 6, k), _list(b, 7, k), np.isfinite(_list(b, 8, k))
                low, high, lag = [], [], []
                for step in range(min(lambda_, len(local) - 1 - lo) + 1):  # the later sample of a pair may be in the halo
                    end = min(hi, len(local) - step)
                    ok = seen[lo:end] & seen[lo + step : end + step]
                    x, y = local[lo:end][ok], local[lo + step : end + step][ok]
                    low.append(np.minimum(x, y)), high.append(np.maximum(x, y)), lag.append(np.full(len(x), step, np.int32))
                low, high, lag = map(np.concatenate, (low, high, lag))
                order = np.lexsort((lag, high, low))
                low, high, lag = low[order], u[high[order]], lag[order]
                at = np.append(np.flatnonzero(np.diff(low, prepend=-1)), len(low))
                for first in range(0, len(at) - 1, 1024):
                    some = at[first : first + 1025]
                    body = [zlib.compress(np.diff(high[i:j], prepend=0).tobytes() + lag[i:j].tobytes(), 1) for i, j in zip(some[:-1], some[1:])]
                    yield pa.record_batch([pa.array(u[low[some[:-1]]]), pa.array(np.full(len(body), noise, np.int32)), pa.array(body, pa.binary())], names=["p", "noise_id", "body"])

    def cells(batches):
        for b in batches:
            for k in range(b.num_rows):
                p, q, v = b.column(0)[k].as_py(), [], []
                for x in b.column(1)[k].as_py():
                    body = zlib.decompress(x["body"])
                    n = len(body) // 12
                    high, lag = np.cumsum(np.frombuffer(body, np.int64, n)), np.frombuffer(body, np.int32, n, 8 * n)
                    q.append(high), v.append(w[x["noise_id"]][lag] * np.where((high == p) & (lag > 0), 2.0, 1.0))
                q, at = np.unique(np.concatenate(q), return_inverse=True)
                v, other = np.bincount(at, np.concatenate(v)), q != p
                mine = np.full(len(q), p, np.int64)
                yield pa.record_batch([pa.array(np.concatenate(x)) for x in ((mine, q[other]), (q, mine[other]), (v, v[other]))], names=["p", "q", "v"])

    sent = pack(tod, lambda_, length).mapInArrow(run, "p long, noise_id int, body binary")
    return sent.groupBy("p").agg(F.collect_list(F.struct("noise_id", "body")).alias("x")).mapInArrow(cells, "p long, q long, v double")
