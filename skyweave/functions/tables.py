"""Table-valued functions for SQL: noise kernels by parameter row, and a small map by one call."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class KernelLags:
    """(lag, w) of a banded noise kernel."""

    def eval(self, fknee: float, sigma2: float, band: int, grid: int):
        from skyweave.functions import kernels as K

        for lag, w in enumerate(K.kernel(fknee, band, sigma2, grid)):
            yield lag, float(w)


class SmallMap:
    """Intensity map (pix, i) of a table argument with columns interval_id, t, pix, d; every partition of the argument is a map.

    A partition is held in memory, so it raises beyond ``MOST`` rows: larger maps go through make_map. Gaps in t raise too."""

    MOST = 1_000_000

    def __init__(self):
        self.rows, self.args = [], None

    def eval(self, row, fknee: float, band: int):
        self.args = (fknee, band)
        self.rows.append((row["interval_id"], row["t"], row["pix"], row["d"]))
        if len(self.rows) > self.MOST:
            raise ValueError(f"more than {self.MOST} rows for one map; use make_map")

    def terminate(self):
        if not self.rows:
            return
        import numpy as np

        from skyweave.functions import kernels as K
        from skyweave.operators import krylov

        self.rows.sort(key=lambda r: r[:2])
        interval, t, pix = (np.array([r[k] for r in self.rows], np.int64) for k in range(3))
        d = np.array([r[3] for r in self.rows], float)
        upix, at = np.unique(pix, return_inverse=True)
        cut = np.concatenate(([0], np.flatnonzero(np.diff(interval)) + 1, [len(d)]))
        if any(np.any(np.diff(t[lo:hi]) != 1) for lo, hi in zip(cut[:-1], cut[1:])):
            raise ValueError("t has gaps or repeats inside an interval")
        w = K.kernel(*self.args)

        def accumulated(y):
            return np.bincount(at, np.concatenate([K.weight(y[lo:hi], w) for lo, hi in zip(cut[:-1], cut[1:])]), len(upix))

        hits = np.bincount(at) * w[0]
        x = krylov.cg(lambda v: accumulated(v[at]), lambda v: v / hits, accumulated(d), tol=1e-12).x
        for p, v in zip(upix.tolist(), x.tolist()):
            yield p, v


kernel_lags = udtf(KernelLags, returnType="lag long, w double")
small_map = udtf(SmallMap, returnType="pix long, i double")


def register(spark: SparkSession) -> None:
    """Make the functions callable in SQL as kernel_lags(...) and small_map(TABLE(...), ...)."""
    spark.udtf.register("kernel_lags", kernel_lags)
    spark.udtf.register("small_map", small_map)
