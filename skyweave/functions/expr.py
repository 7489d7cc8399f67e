"""Column functions: responses, spectra, small dense algebra, deterministic noise."""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def col(x) -> Column:
    return F.col(x) if isinstance(x, str) else x if isinstance(x, Column) else F.lit(x)


def stokes_weights(phi, nstokes: int = 3) -> Column:
    """(1) for intensity, (1, cos 2 phi, sin 2 phi) for a polarised sample."""
    if nstokes == 1:
        return F.array(F.lit(1.0))
    if nstokes != 3:
        raise ValueError("nstokes is 1 or 3")
    return F.array(F.lit(1.0), F.cos(2 * col(phi)), F.sin(2 * col(phi)))


def psd(f, sigma2=1.0, fknee=0.1, t_samp=1.0, slope=2.0) -> Column:
    f, fk = col(f), col(fknee)
    return F.when((f == 0) & (fk > 0), F.lit(float("inf"))).otherwise(col(sigma2) * col(t_samp) * (1 + F.when(fk > 0, F.pow(fk / F.when(f == 0, F.lit(1.0)).otherwise(f), col(slope))).otherwise(0.0)))


def inverse_psd(f, sigma2=1.0, fknee=0.1, t_samp=1.0, slope=2.0) -> Column:
    f, fk, s = col(f), col(fknee), col(slope)
    return F.when(fk > 0, F.pow(f, s) / (col(sigma2) * col(t_samp) * (F.pow(f, s) + F.pow(fk, s)))).otherwise(1 / (col(sigma2) * col(t_samp)))


def inv3_sym(a, b, c, d, e, f) -> list[Column]:
    """Upper triangle of the inverse of [[a, b, c], [b, d, e], [c, e, f]] by cofactors."""
    a, b, c, d, e, f = map(col, (a, b, c, d, e, f))
    det = a * (d * f - e * e) - b * (b * f - c * e) + c * (b * e - c * d)
    return [x / det for x in (d * f - e * e, c * e - b * f, b * e - c * d, a * f - c * c, b * c - a * e, a * d - b * b)]


def let(value: Column, fn) -> Column:
    """fn(value) with ``value`` evaluated once: pushed through projections and filters it is still one expression."""
    return F.element_at(F.transform(F.array(value), fn), 1)


def rcond3_sym(a, b, c, d, e, f) -> Column:
    """Smallest over largest eigenvalue of the symmetric 3x3 matrix (closed trigonometric form)."""
    def spread(m):
        q = (m["a"] + m["d"] + m["f"]) / 3
        A, D, G = m["a"] - q, m["d"] - q, m["f"] - q
        p = F.sqrt((A * A + D * D + G * G + 2 * (m["b"] * m["b"] + m["c"] * m["c"] + m["e"] * m["e"])) / 6)
        return m.withField("q", q).withField("p", p)

    def angle(m):
        s = F.when(m["p"] == 0, F.lit(1.0)).otherwise(m["p"])
        A, D, G = (m["a"] - m["q"]) / s, (m["d"] - m["q"]) / s, (m["f"] - m["q"]) / s
        B, C, E = m["b"] / s, m["c"] / s, m["e"] / s
        half = (A * (D * G - E * E) - B * (B * G - C * E) + C * (B * E - C * D)) / 2
        return F.struct(m["q"].alias("q"), m["p"].alias("p"), (F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), half))) / 3).alias("t"))

    def ends(m):
        return F.struct((m["q"] + 2 * m["p"] * F.cos(m["t"])).alias("high"), (m["q"] + 2 * m["p"] * F.cos(m["t"] + 2 * math.pi / 3)).alias("low"))

    def ratio(m):
        return F.when(m["high"] <= 0, F.lit(0.0)).otherwise(F.greatest(m["low"], F.lit(0.0)) / m["high"])

    block = F.struct(*(col(x).cast("double").alias(k) for x, k in zip((a, b, c, d, e, f), "abcdef")))
    return let(let(let(let(block, spread), angle), ends), ratio)


def hash_gauss(seed: int, *columns) -> Column:
    """Standard normal from hashed columns (Box-Muller): the same under any partitioning."""
    u = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), *columns), 11) + 1) / F.lit(float(1 << 53) + 1)
    v = F.shiftrightunsigned(F.xxhash64(F.lit(seed + 1), *columns), 11) / F.lit(float(1 << 53))
    return F.sqrt(-2 * F.log(u)) * F.cos(2 * math.pi * v)


def cg_bound(kappa, j) -> Column:
    """Bound on the A-norm error after j steps."""
    root = F.sqrt(col(kappa))
    return 2 * F.pow((root - 1) / (root + 1), col(j))


def register(spark: SparkSession) -> None:
    """SQL functions of the engine."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sky_stokes(phi DOUBLE) RETURNS ARRAY<DOUBLE> RETURN array(1D, cos(2 * phi), sin(2 * phi))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sky_inverse_psd(f DOUBLE, sigma2 DOUBLE, fknee DOUBLE) RETURNS DOUBLE RETURN f * f / (sigma2 * (f * f + fknee * fknee))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sky_psd(f DOUBLE, sigma2 DOUBLE, fknee DOUBLE) RETURNS DOUBLE RETURN sigma2 * (1 + fknee * fknee / (f * f))")
