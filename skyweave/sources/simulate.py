"""Simulated samples: d = P x + n with a Gaussian sky and piece-wise stationary noise of a given spectrum."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skyweave.functions import expr, kernels
from skyweave.operators import pointing
from skyweave.operators.system import weight_fft


def colour_kernel(fknee: float, sigma2: float = 1.0, grid_n: int = 1024, slope: float = 2.0) -> np.ndarray:
    """First row of the symmetric filter that gives white samples the spectrum sigma2 (1 + (fknee / f)**slope); flat below the grid's lowest frequency."""
    f = np.maximum(np.arange(grid_n // 2 + 1), 1) / grid_n
    return np.fft.irfft(np.sqrt(sigma2 * (1 + (fknee / f) ** slope)), grid_n)[: grid_n // 2 + 1]


def noise(tod: DataFrame, knees: dict[int, float], sigma2: float = 1.0, seed: int = 1, grid_n: int = 1024, length: int = 1 << 20) -> DataFrame:
    """(interval_id, t, n): noise of each interval's spectrum, by noise_id. White samples are a hash of (seed, interval, t), also half a grid beyond both
    ends, and a filter of that width colours them chunk by chunk: the same under any partitioning, stationary up to the ends, for intervals of any length."""
    half = grid_n // 2
    each = tod.groupBy("interval_id").agg(F.min("t").alias("lo"), F.max("t").alias("hi"), F.first("noise_id").alias("noise_id"))
    margin = each.select("interval_id", "noise_id", F.explode(F.concat(F.sequence(F.col("lo") - half, F.col("lo") - 1), F.sequence(F.col("hi") + 1, F.col("hi") + half))).alias("t"))
    slots = tod.select("interval_id", "noise_id", "t").unionByName(margin)
    white = slots.select("interval_id", (F.col("t") + half).alias("t"), "noise_id", F.lit(0).cast("long").alias("pix"), F.lit(0.0).alias("phi"), expr.hash_gauss(seed, F.col("interval_id"), F.col("t")).alias("d"))
    model = kernels.Stationary({k: colour_kernel(fk, sigma2, grid_n) for k, fk in knees.items()}, check=False)
    out = weight_fft(white, model, length).select("interval_id", (F.col("t") - half).alias("t"), F.col("y").alias("n"))
    return out.join(tod.select("interval_id", "t"), ["interval_id", "t"], "left_semi")


def gaussian_sky(pix: Column, rows: int, cols: int, seed: int = 1, modes: int = 64, beam: float = 2.0, amplitude: float = 1.0) -> Column:
    """A Gaussian random field on a grid of rows x cols pixels: ``modes`` plane waves of seeded directions and normal amplitudes, those finer than
    the Gaussian ``beam`` (in pixels) damped. A column expression, so any partition has the same sky."""
    rng = np.random.default_rng(seed)
    kx, ky = rng.integers(0, cols // 4 + 1, modes), rng.integers(-(rows // 4), rows // 4 + 1, modes)
    size = np.hypot(kx / cols, ky / rows) * 2 * math.pi
    a = rng.standard_normal((2, modes)) * amplitude * np.exp(-((size * beam) ** 2) / 2) / np.sqrt(modes / 2)
    x, y = F.pmod(pix, F.lit(cols)) / cols, F.floor(pix / cols) / rows
    out = F.lit(0.0)
    for k in range(modes):
        turn = 2 * math.pi * (float(kx[k]) * x + float(ky[k]) * y)
        out = out + float(a[0, k]) * F.cos(turn) + float(a[1, k]) * F.sin(turn)
    return out


def make_tod(pointing_rows: DataFrame, sky: DataFrame, nstokes: int = 1, knees: dict[int, float] | None = None, sigma2: float = 1.0, seed: int = 1, **how) -> DataFrame:
    """d = P x + n for pointing (interval_id, t, pix, phi, noise_id) and a wide map; without ``knees`` no noise."""
    base = pointing.expand(pointing_rows.drop("d"), sky, nstokes).withColumnRenamed("y", "d")
    if knees is None:
        return base
    n = noise(pointing_rows, knees, sigma2, seed, **how)
    return base.join(n, ["interval_id", "t"]).withColumn("d", F.col("d") + F.col("n")).drop("n")
