"""Queries of the map-making engine and their SQL."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from skyweave import oracles as O
from skyweave.functions import expr as X
from skyweave.functions import kernels as K
from skyweave.functions import tables
from skyweave.operators import krylov, precond
from skyweave.operators import pointing as P
from skyweave.operators import solve as S
from skyweave.operators import system as Y
from skyweave.plans.lineage import cut
from skyweave.sources import simulate as SIM
from skyweave.sources import workloads as WL
from skyweave.sources.scan import pixels
from skyweave.sources.tables import load

TIGHT = 1e-12
Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(fn):
        Q[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return add


def r6(c, n: int = 6):
    return F.round(c, n) + F.lit(0.0)


def model_w0():
    return K.Stationary({0: K.kernel(0.05, 128), 1: K.kernel(0.1, 128)})


def kernel_rows(spark, kernels: dict[int, np.ndarray]) -> DataFrame:
    return spark.createDataFrame([(k, i, float(v)) for k, w in kernels.items() for i, v in enumerate(w)], "noise_id int, lag long, w double")


def rounded(m: DataFrame, n: int = 6) -> DataFrame:
    return m.select("pix", *(r6(F.col(c), n).alias(c) for c in m.columns if c != "pix"))


# ---- maps of the event stream: one answer, many solvers ----

def _w0(**how):
    return lambda spark, d: rounded(S.make_map(WL.tod_w0(spark, d), model_w0(), tol=TIGHT, **how).map())


for _name, _how in {
    "flagship_map_w0": {}, "map_w0_none": {"prec": "none"}, "map_w0_ones": {"prec": "ones"}, "map_w0_apriori": {"prec": "apriori"}, "map_w0_apriori_r1": {"prec": "apriori", "rank": 1},
    "map_w0_aposteriori": {"prec": "aposteriori"}, "map_w0_def2": {"prec": "apriori", "variant": "def2"}, "map_w0_deflation": {"prec": "deflation", "rank": 5}, "map_w0_gmres": {"solver": "gmres"}, "map_w0_halo_split": {"length": 150},
}.items():
    query(_name, O.MAP_W0)(_w0(**_how))


@query("map_w0_direct", O.MAP_W0)
def _(spark, d):
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    x = S.direct(op)
    op.close()
    return rounded(op.table(x))


@query("map_w0_pol_apriori", O.MAP_W0_POL)
def _(spark, d):
    return rounded(S.make_map(WL.tod_w0(spark, d, True), model_w0(), 3, "apriori", tol=TIGHT).map())


@query("map_w0_pol_aposteriori", O.MAP_W0_POL)
def _(spark, d):
    return rounded(S.make_map(WL.tod_w0(spark, d, True), model_w0(), 3, "aposteriori", tol=TIGHT).map())


@query("map_w0_distributed_apriori", O.MAP_W0)
def _(spark, d):
    """Two-level, by tables: the plan is made to choose them by a budget of nothing."""
    return rounded(S.solve_map(WL.tod_w0(spark, d), model_w0(), prec="apriori", rank=10, tol=1e-11, budget=1))


@query("map_w0_pol_distributed_apriori", O.MAP_W0_POL)
def _(spark, d):
    return rounded(S.distributed_cg(Y.DistributedOperator(WL.tod_w0(spark, d, True), model_w0(), 3), 1e-11, rank=10)[0])


@query("map_w4_fourier", O.fourier_map(O.W4, 0.1))
def _(spark, d):
    """The map with weights diagonal in each interval's Fourier modes; the mean of an interval counts as half its lowest mode, so that the map's offset is determined."""
    return rounded(S.make_map(WL.tod_w4(spark, d), K.Circulant({0: 0.1}, lowest=0.5), tol=TIGHT).map())


@query("map_w5_full_block", O.small_map(O.W5, 0.1, 512, whole=True))
def _(spark, d):
    """Blocks that are not limited in band."""
    return rounded(S.make_map(WL.tod_w5(spark, d), K.Stationary({0: K.kernel(0.1, None)}, check=False), tol=TIGHT).map())


@query("map_w0_distributed", O.MAP_W0)
def _(spark, d):
    return rounded(S.distributed_cg(Y.DistributedOperator(WL.tod_w0(spark, d), model_w0()), tol=1e-11)[0])


@query("map_w0_pol", O.MAP_W0_POL)
def _(spark, d):
    return rounded(S.make_map(WL.tod_w0(spark, d, True), model_w0(), 3, tol=TIGHT).map())


@query("map_w4_exact", O.small_map(O.W4, 0.1, 8))
def _(spark, d):
    return rounded(S.make_map(WL.tod_w4(spark, d), K.Stationary({0: K.kernel(0.1, 8)}), tol=TIGHT).map())


@query("map_w5_short", O.small_map(O.W5, 0.1, 64))
def _(spark, d):
    return rounded(S.make_map(WL.tod_w5(spark, d), K.Stationary({0: K.kernel(0.1, 64)}), tol=TIGHT).map())


_GRAM = """g AS (SELECT i, j, sum(CAST(embedding[i] AS DOUBLE) * CAST(embedding[j] AS DOUBLE)) / (SELECT count(*) FROM embeddings) + CASE WHEN i = j THEN 0.01 ELSE 0 END AS v FROM embeddings, range(1, 65) a(i), range(1, 65) b(j) GROUP BY i, j)"""


@query("map_w7_spd", f"WITH RECURSIVE {O.solved(_GRAM + ', cells AS (SELECT i AS p, j AS q, v FROM g), bv AS (SELECT i AS p, sum(CAST(embedding[i] AS DOUBLE) * label) AS v FROM embeddings, range(1, 65) a(i) GROUP BY i)')} SELECT CAST(p AS BIGINT) AS k, round(x, 6) + 0.0 AS v FROM sol")
def _(spark, d):
    """A generic positive system: Gram matrix of the embeddings by one native aggregation, then CG."""
    e = load(spark, d, "embeddings").select(F.transform("embedding", lambda x: x.cast("double")).alias("x"), "label")
    cells = e.select(F.posexplode("x").alias("i", "a"), "x", "label")
    rows = cells.groupBy("i").agg(F.sum(F.col("a") * F.col("label")).alias("b"), *(F.sum(F.col("a") * F.col("x")[j]).alias(f"g{j}") for j in range(64)), F.count("*").alias("n")).orderBy("i").collect()  # 64 rows
    g = np.array([[r[f"g{j}"] for j in range(64)] for r in rows]) / rows[0]["n"] + 0.01 * np.eye(64)
    s = krylov.cg(lambda v: g @ v, precond.identity(), np.array([r["b"] for r in rows]), tol=1e-13)
    return spark.createDataFrame([(i + 1, float(v)) for i, v in enumerate(s.x)], "k long, v double").select("k", r6(F.col("v")).alias("v"))


@query("unbiased_noise_free", f"WITH {O.W0} SELECT DISTINCT pix, round(10 + 3 * sin(pix * 0.37) + 2 * cos(pix * 0.11), 6) + 0.0 AS i FROM tod")
def _(spark, d):
    tod = WL.tod_w0(spark, d).withColumn("d", WL.sky(F.col("pix")))
    return rounded(S.make_map(tod, model_w0(), prec="apriori", tol=TIGHT).map())


# ---- geometry ----

for _w, _tod, _cte in (("w0", WL.tod_w0, O.W0), ("w1", WL.tod_w1, O.W1), ("w2", WL.tod_w2, O.W2), ("w3", WL.tod_w3, O.W3)):
    query(f"hit_map_{_w}", f"WITH {_cte} SELECT CAST(pix AS BIGINT) AS pix, count(*) AS hits FROM tod GROUP BY pix")(lambda s, d, f=_tod: P.hit_map(f(s, d)))
    query(f"tod_index_{_w}", f"WITH {_cte} SELECT CAST(interval_id AS BIGINT) AS interval_id, CAST(t AS BIGINT) AS t, CAST(pix AS BIGINT) AS pix, CAST(d AS DOUBLE) AS d FROM tod")(lambda s, d, f=_tod: f(s, d).select("interval_id", "t", "pix", "d"))
    query(f"white_coadd_{_w}", f"WITH {_cte} SELECT CAST(pix AS BIGINT) AS pix, round(avg(d) + 1e-7, 4) + 0.0 AS i FROM tod GROUP BY pix")(lambda s, d, f=_tod: P.coadd(f(s, d)).select("pix", r6(F.col("i") + 1e-7, 4).alias("i")))
    query(f"scan_stats_{_w}", f"WITH {_cte}, h AS (SELECT pix, count(*) AS hits FROM tod GROUP BY pix) SELECT count(*) AS n_pix, CAST(sum(hits) AS BIGINT) AS n_t, min(hits) AS least, max(hits) AS most, round(avg(hits), 6) AS mean, round(stddev_pop(hits), 6) AS spread FROM h")(lambda s, d, f=_tod: P.scan_stats(f(s, d)))
for _w, _tod, _cte in (("w0", WL.tod_w0, O.W0), ("w3", WL.tod_w3, O.W3)):
    query(f"hits_by_interval_{_w}", f"WITH {_cte} SELECT CAST(pix AS BIGINT) AS pix, CAST(interval_id AS BIGINT) AS interval_id, count(*) AS hits FROM tod GROUP BY ALL")(lambda s, d, f=_tod: P.hits_by_interval(f(s, d)))
    query(f"pixel_multiplicity_{_w}", f"WITH {_cte} SELECT CAST(pix AS BIGINT) AS pix, count(DISTINCT interval_id) AS mult FROM tod GROUP BY pix")(lambda s, d, f=_tod: P.multiplicity(f(s, d)))
    query(f"comm_bytes_{_w}", f"WITH {_cte} SELECT CAST(interval_id AS BIGINT) AS interval_id, count(DISTINCT pix) * 8 AS bytes FROM tod GROUP BY interval_id")(lambda s, d, f=_tod: P.comm_bytes(f(s, d)))

_STEP = {"polariser_fast_w1": (O.W1, "t % 4", lambda s, d: WL.tod_w1(s, d, "fast")), "polariser_medium_w1": (O.W1, "sweep % 4", lambda s, d: WL.tod_w1(s, d, "medium")), "polariser_medium_w2": (O.W2, "year % 4", lambda s, d: WL.tod_w2(s, d, polariser="medium")), "polariser_medium_w3": (O.W3, "year % 4", lambda s, d: WL.tod_w3(s, d, "medium")), "polariser_circle_w3": (O.W3, "interval_id % 4", lambda s, d: WL.tod_w3(s, d, "circle")), "polariser_fast_w0": (O.W0P, "g % 4", lambda s, d: WL.tod_w0(s, d, True))}
for _name, (_cte, _sql, _f) in _STEP.items():
    query(_name, f"WITH {_cte} SELECT CAST(pix AS BIGINT) AS pix, CAST({_sql} AS BIGINT) AS step, count(*) AS n FROM tod GROUP BY ALL")(lambda s, d, f=_f: P.attack_angles(f(s, d)))
query("polariser_slow_w3", f"WITH {O.W3} SELECT CAST(interval_id + n * pass AS BIGINT) AS interval_id, CAST(pix AS BIGINT) AS pix, CAST(pass AS BIGINT) AS step, count(*) AS n FROM tod, nc, range(4) r(pass) GROUP BY ALL")(lambda s, d: WL.tod_w3(s, d, "slow").groupBy("interval_id", "pix", F.round(F.col("phi") * 4 / math.pi).cast("long").alias("step")).agg(F.count("*").alias("n")))

# ---- pointing ----

query("stokes_weights_w0", f"WITH {O.W0P} SELECT interval_id, t, round(cos(2 * phi), 6) + 0.0 AS c, round(sin(2 * phi), 6) + 0.0 AS s FROM tod")(lambda s, d: WL.tod_w0(s, d, True).withColumn("r", X.stokes_weights("phi")).select("interval_id", "t", r6(F.col("r")[1]).alias("c"), r6(F.col("r")[2]).alias("s")))
_SKY_SQL = "10 + 3 * sin(pix * 0.37) + 2 * cos(pix * 0.11)"


@query("expand_w0", f"WITH {O.W0P} SELECT interval_id, t, round({_SKY_SQL} + 0.5 * pix * cos(2 * phi) - sin(2 * phi), 6) + 0.0 AS y FROM tod")
def _(spark, d):
    tod = WL.tod_w0(spark, d, True)
    m = tod.select("pix").distinct().select("pix", WL.sky(F.col("pix")).alias("i"), (0.5 * F.col("pix")).alias("q"), F.lit(-1.0).alias("u"))
    return P.expand(tod, m, 3).select("interval_id", "t", r6(F.col("y")).alias("y"))


query("accumulate_w0_int", f"WITH {O.W0} SELECT pix, round(sum(d), 4) + 0.0 AS i FROM tod GROUP BY pix")(lambda s, d: rounded(P.accumulate(WL.tod_w0(s, d), "d"), 4))
query("accumulate_w0_pol", f"WITH {O.W0P} SELECT pix, round(sum(d), 4) + 0.0 AS i, round(sum(d * cos(2 * phi)), 4) + 0.0 AS q, round(sum(d * sin(2 * phi)), 4) + 0.0 AS u FROM tod GROUP BY pix")(lambda s, d: rounded(P.accumulate(WL.tod_w0(s, d, True), "d", 3), 4))
_CUT = "ok AS (SELECT pix, count(DISTINCT step) >= 3 AS keep FROM (SELECT pix, {step} AS step FROM tod) GROUP BY pix)"
for _w, _cte, _step, _f in (("w2", O.W2, "year % 4", lambda s, d: WL.tod_w2(s, d, polariser="medium")), ("w3", O.W3, "interval_id % 4", lambda s, d: WL.tod_w3(s, d, "circle"))):
    # with angles at multiples of 45 degrees a block is well-conditioned exactly when three of the four steps occur
    query(f"pixel_cut_{_w}", f"WITH {_cte}, {_CUT.format(step=_step)} SELECT CAST(tod.pix AS BIGINT) AS pix, count(*) AS n FROM tod JOIN ok ON ok.pix = tod.pix WHERE keep GROUP BY tod.pix")(lambda s, d, f=_f: P.pointed(P.pixel_cut(f(s, d))[0]).groupBy("pix").agg(F.count("*").alias("n")))
    query(f"pixel_cut_anti_{_w}", f"WITH {_cte}, {_CUT.format(step=_step)} SELECT CAST(pix AS BIGINT) AS pix FROM ok WHERE NOT keep")(lambda s, d, f=_f: P.pixel_cut(f(s, d))[1].select("pix"))


@query("asof_pointing", "SELECT o.o_orderkey, max(e.event_id) AS event_id FROM orders o LEFT JOIN events e ON e.user_id = o.o_custkey AND e.event_id <= o.o_orderkey GROUP BY o.o_orderkey")
def _(spark, d):
    e = load(spark, d, "events").select(F.col("user_id").alias("key"), F.col("event_id").alias("at"), "event_id")
    o = load(spark, d, "orders").select(F.col("o_custkey").alias("key"), F.col("o_orderkey").alias("at"), "o_orderkey")
    return P.attach_asof(o, e, "key", "at", ["event_id"]).select("o_orderkey", "event_id")


@query("interval_assign", "WITH n AS (SELECT max(event_id) // 700 + 1 AS n FROM events), p AS (SELECT i AS interval_id, i * 700 AS lo, i * 700 + 499 AS hi FROM n, range(n.n) r(i)) SELECT event_id, interval_id FROM events JOIN p ON event_id BETWEEN lo AND hi")
def _(spark, d):
    pieces = load(spark, d, "events").agg(F.max("event_id")).first()[0] // 700 + 1
    p = spark.range(pieces).select(F.col("id").alias("interval_id"), (F.col("id") * 700).alias("lo"), (F.col("id") * 700 + 499).alias("hi"))
    return P.interval_assign(load(spark, d, "events").select("event_id"), p, "event_id", 700).select("event_id", "interval_id")


query("band_pairs_w0", f"WITH {O.W0} SELECT a.pix, b.pix AS pix2, CAST(abs(a.t - b.t) AS BIGINT) AS lag, count(*) AS n FROM tod a JOIN tod b ON a.interval_id = b.interval_id AND b.t BETWEEN a.t - 16 AND a.t + 16 GROUP BY ALL")(lambda s, d: P.band_pairs(WL.tod_w0(s, d), 16).groupBy("pix", "pix2", F.col("lag").cast("long").alias("lag")).agg(F.count("*").alias("n")))
query("overlap_intersect", f"WITH {O.W3} SELECT CAST(pix AS BIGINT) AS pix FROM tod WHERE interval_id = 0 INTERSECT SELECT CAST(pix AS BIGINT) FROM tod WHERE interval_id = 1")(lambda s, d: P.overlap(WL.tod_w3(s, d), 0, 1))
query("topk_hits", f"WITH {O.W0} SELECT pix, count(*) AS hits FROM tod GROUP BY pix ORDER BY hits DESC, pix LIMIT 10")(lambda s, d: P.hit_map(WL.tod_w0(s, d)).orderBy(F.desc("hits"), "pix").limit(10))

# ---- noise ----

def days(spark, d) -> DataFrame:
    """(interval_id, n, noise_id): the days of the event stream and their numbers of samples."""
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("long")
    return load(spark, d, "events").groupBy(day.alias("interval_id")).agg(F.count("*").alias("n")).withColumn("noise_id", (F.col("interval_id") % 2).cast("int"))


def _modes(spark, d, first: int) -> DataFrame:
    """The Fourier modes of every day's samples, up to half its length."""
    return days(spark, d).where(F.col("n") >= 2).select("interval_id", "n", F.explode(F.sequence(F.lit(first).cast("long"), F.floor(F.col("n") / 2))).alias("m"))


def _by_day(spark, d, rows: DataFrame, *columns: str) -> DataFrame:
    """Rows by noise_id for each day of that noise."""
    return days(spark, d).select("interval_id", "noise_id").join(F.broadcast(rows), "noise_id").select("interval_id", *columns)


query("psd_table", f"WITH {O.DAYS} SELECT interval_id, m, round(1 + (0.1 / (m / CAST(n AS DOUBLE)))**2, 6) + 0.0 AS p FROM days, range(1, n // 2 + 1) r(m)")(lambda s, d: _modes(s, d, 1).select("interval_id", "m", r6(X.psd(F.col("m") / F.col("n"))).alias("p")))
query("inverse_psd_table", f"WITH {O.DAYS} SELECT interval_id, m, round((m / CAST(n AS DOUBLE))**2 / ((m / CAST(n AS DOUBLE))**2 + 0.01), 6) + 0.0 AS p FROM days, range(n // 2 + 1) r(m) WHERE n >= 2")(lambda s, d: _modes(s, d, 0).select("interval_id", "m", r6(X.inverse_psd(F.col("m") / F.col("n"))).alias("p")))
for _kind, _win in (("apodized", "exp(-2 * (lag / 128.0)**2)"), ("hardcut", "1.0")):
    _sql = f"WITH {O.DAYS}, {O.KERN0} SELECT interval_id, lag, round(w{'' if _kind == 'apodized' else ' / exp(-2 * (lag / 128.0)**2)'}, 9) + 0.0 AS w FROM days JOIN kern ON kern.noise_id = interval_id % 2"
    query(f"kernel_{_kind}", _sql)(lambda s, d, k=_kind: _by_day(s, d, kernel_rows(s, {n: K.kernel(f, 128, kind="gauss" if k == "apodized" else "cut") for n, f in ((0, 0.05), (1, 0.1))}), "lag", r6(F.col("w"), 9).alias("w")))


@query("apodized_spectrum", f"WITH {O.DAYS}, {O.KERN0} SELECT interval_id, m, round(sum(w * cos(2 * pi() * ((m * lag) % 1024) / 1024) * CASE WHEN lag = 0 THEN 1 ELSE 2 END), 6) + 0.0 AS v FROM days JOIN kern ON kern.noise_id = interval_id % 2, range(513) r(m) GROUP BY interval_id, m")
def _(spark, d):
    """Spectrum of each day's weights."""
    rows = [(k, i, float(x)) for k, w in model_w0().kernels.items() for i, x in enumerate(K.apodized_spectrum(w, 1024))]
    return _by_day(spark, d, spark.createDataFrame(rows, "noise_id int, m long, v double"), "m", r6(F.col("v")).alias("v"))


# a band of a circle's whole length, one circle a supplier
query("deflection_freq", "SELECT l_suppkey AS interval_id, count(*) AS n, round(1 / (pi() * count(*)), 9) AS f FROM lineitem GROUP BY l_suppkey")(lambda s, d: load(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("interval_id")).agg(F.count("*").alias("n")).select("interval_id", "n", F.round(1 / (math.pi * F.col("n")), 9).alias("f")))


@query("apodisation_study")
def _(spark, d):
    """First rows and lowest spectrum values over band widths, with each day's knee; the printed growing window is rejected. ``whole``: the band is within the day."""
    rows = []
    for noise_id, fk in ((0, 0.05), (1, 0.1)):
        for lam in (10000, 2000, 500, 100):
            w = K.kernel(fk, lam, grid_n=32768)
            v = K.apodized_spectrum(w, 32768)
            grow = K.kernel(fk, lam, grid_n=32768, kind="cut") * np.exp(2.0 * (np.arange(lam + 1) / lam) ** 2)
            rows.append((noise_id, lam, K.deflection_frequency(lam), float(w[0]), float(v.min()), float(K.apodized_spectrum(grow, 32768).min())))
    bands = spark.createDataFrame(rows, "noise_id int, lambda int, f_defl double, w0 double, lowest double, lowest_if_growing double")
    return days(spark, d).join(F.broadcast(bands), "noise_id").select("interval_id", (F.col("lambda") < F.col("n")).alias("whole"), *bands.columns[1:])


_YSQL = f"WITH {O.W0}, {O.KERN0}, {O.Y0} SELECT interval_id, CAST(t AS BIGINT) AS t, round(y, 5) + 0.0 AS y FROM y0"
query("noise_weight_lagjoin_w0", _YSQL)(lambda s, d: Y.weight_lag_join(WL.tod_w0(s, d), kernel_rows(s, model_w0().kernels)).select("interval_id", "t", r6(F.col("y"), 5).alias("y")))
query("noise_weight_fir_w0", _YSQL)(lambda s, d: Y.weight_fir(WL.tod_w0(s, d), kernel_rows(s, model_w0().kernels), 128).select("interval_id", "t", r6(F.col("y"), 5).alias("y")))
query("noise_weight_fft_w0", _YSQL)(lambda s, d: Y.weight_fft(WL.tod_w0(s, d), model_w0(), 100).select("interval_id", "t", r6(F.col("y"), 5).alias("y")))


@query("fourier_weight_w5", f"""WITH {O.W5}, n AS (SELECT interval_id, count(*) AS n FROM tod GROUP BY 1), ip AS (SELECT interval_id, n, m, (least(m, n - m) / CAST(n AS DOUBLE))**2 / ((least(m, n - m) / CAST(n AS DOUBLE))**2 + 0.01) AS p FROM n, range(n.n) r(m)),
h AS (SELECT interval_id, n, k, sum(p * cos(2 * pi() * m * k / n) / n) AS w FROM ip, range(ip.n) s(k) GROUP BY interval_id, n, k)
SELECT a.interval_id, CAST(a.t AS BIGINT) AS t, round(sum(w * b.d), 5) + 0.0 AS y FROM tod a JOIN tod b USING (interval_id) JOIN h ON h.interval_id = a.interval_id AND h.k = abs(a.t - b.t) GROUP BY ALL""")
def _(spark, d):
    return Y.weight_fft(WL.tod_w5(spark, d), K.Circulant({0: 0.1})).select("interval_id", "t", r6(F.col("y"), 5).alias("y"))


query("white_weight_w0", f"WITH {O.W0} SELECT interval_id, CAST(t AS BIGINT) AS t, round(d / 4, 6) + 0.0 AS y FROM tod")(lambda s, d: Y.weight_fft(WL.tod_w0(s, d), K.Stationary({k: K.white_kernel(4.0) for k in (0, 1)})).select("interval_id", "t", r6(F.col("y")).alias("y")))
# a signal at the rate at which a pixel is seen
query("band_rules", "SELECT user_id AS pix, CAST(ceil(1 / (pi() * f)) AS BIGINT) AS lossless, CAST(floor(1 / (pi() * f)) AS BIGINT) AS white FROM (SELECT user_id, count(*) / CAST((SELECT count(*) FROM events) AS DOUBLE) AS f FROM events GROUP BY user_id)")(lambda s, d: _band_rules(s, d))


def _band_rules(spark, d) -> DataFrame:
    e = load(spark, d, "events").select(F.col("user_id").alias("pix"))
    f = e.groupBy("pix").agg(F.count("*").alias("n")).join(F.broadcast(e.agg(F.count("*").alias("all")))).select("pix", (F.col("n") / F.col("all")).alias("f"))
    band = 1 / (math.pi * F.col("f"))
    return f.select("pix", F.ceil(band).alias("lossless"), F.floor(band).alias("white"))


query("pixel_cut_slots_w3", f"WITH {O.W3}, {_CUT.format(step='interval_id % 4')} SELECT CAST(interval_id AS BIGINT) AS interval_id, CAST(t AS BIGINT) AS t, CASE WHEN keep THEN CAST(tod.pix AS BIGINT) ELSE -1 END AS pix FROM tod JOIN ok ON ok.pix = tod.pix")(lambda s, d: P.pixel_cut(WL.tod_w3(s, d, "circle"))[0].select("interval_id", "t", "pix"))
query("pixel_cut_split_w3", f"WITH {O.W3}, {_CUT.format(step='interval_id % 4')}, k AS (SELECT interval_id, t, t - row_number() OVER (PARTITION BY interval_id ORDER BY t) AS run FROM tod JOIN ok ON ok.pix = tod.pix WHERE keep), g AS (SELECT interval_id, run, count(*) AS n FROM k GROUP BY ALL) SELECT n, count(*) AS pieces FROM g GROUP BY n")(lambda s, d: P.pixel_cut(WL.tod_w3(s, d, "circle"), gap="split")[0].groupBy("interval_id").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("pieces")))


@query("moving_fir", f"WITH {O.W0} SELECT interval_id, CAST(t AS BIGINT) AS t, round(avg(d) OVER (PARTITION BY interval_id ORDER BY t ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING), 5) + 0.0 AS y FROM tod")
def _(spark, d):
    return WL.tod_w0(spark, d).select("interval_id", "t", r6(F.avg("d").over(W.partitionBy("interval_id").orderBy("t").rowsBetween(-3, 3)), 5).alias("y"))


# ---- the system ----

query("rhs_w0", f"WITH {O.W0}, {O.KERN0}, {O.Y0} SELECT pix, round(sum(y), 5) + 0.0 AS i FROM y0 GROUP BY pix")(lambda s, d: rounded((op := Y.NormalOperator(WL.tod_w0(s, d), model_w0())).table(op.rhs()), 5))
query("system_matrix_w0", f"WITH {O.W0}, {O.KERN0}, {O.A0} SELECT p, q, round(v, 6) + 0.0 AS v FROM am")(lambda s, d: Y.explicit(WL.tod_w0(s, d), kernel_rows(s, model_w0().kernels), 128).select("p", "q", r6(F.col("v")).alias("v")))


@query("operator_apply_w0", f"WITH {O.W0}, {O.KERN0}, {O.A0}, h AS (SELECT pix, count(*) AS n FROM tod GROUP BY pix) SELECT p AS pix, round(sum(v), 5) + 0.0 AS ones, round(sum(v * n), 4) + 0.0 AS hits FROM am JOIN h ON h.pix = q GROUP BY p")
def _(spark, d):
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    z = op.apply_many(np.stack((np.ones(op.n), op.hits()[1].sum(axis=1)), axis=1))
    return spark.createDataFrame([(int(p), float(a), float(b)) for p, (a, b) in zip(op.pixels, z)], "pix long, ones double, hits double").select("pix", r6(F.col("ones"), 5).alias("ones"), r6(F.col("hits"), 4).alias("hits"))


@query("operator_apply_distributed_w0", f"WITH {O.W0}, {O.KERN0}, {O.A0} SELECT p AS pix, round(sum(v), 5) + 0.0 AS ones FROM am GROUP BY p")
def _(spark, d):
    op = Y.DistributedOperator(WL.tod_w0(spark, d), model_w0())
    return op.apply(op.lists.select("pix").distinct().withColumn("v0", F.lit(1.0))).select("pix", r6(F.col("v0"), 5).alias("ones"))


_BD = "c11, c12, c13, c22, c23, c33"
query("bd_blocks_int", f"WITH {O.W0}, {O.KERN0} SELECT pix, round(sum(w), 6) AS c11 FROM tod JOIN kern ON kern.noise_id = tod.noise_id AND lag = 0 GROUP BY pix")(lambda s, d: P.stokes_blocks(WL.tod_w0(s, d), F.create_map(*(F.lit(x) for k, v in model_w0().kernels.items() for x in (k, float(v[0]))))[F.col("noise_id")]).select("pix", F.round("c11", 6).alias("c11")))
query("bd_blocks_pol", f"WITH {O.W0P}, {O.BD3} SELECT pix, {', '.join(f'round({c}, 6) + 0.0 AS {c}' for c in _BD.split(', '))} FROM bl")(lambda s, d: rounded(P.stokes_blocks(WL.tod_w0(s, d, True))))
_DET = "(c11*(c22*c33-c23*c23)-c12*(c12*c33-c13*c23)+c13*(c12*c23-c13*c22))"
query("bd_inverse_pol", f"WITH {O.W0P}, {O.BD3} SELECT pix, round((c22*c33-c23*c23)/{_DET}, 6) + 0.0 AS k11, round((c13*c23-c12*c33)/{_DET}, 6) + 0.0 AS k12, round((c11*c22-c12*c12)/{_DET}, 6) + 0.0 AS k33 FROM bl")(lambda s, d: rounded(P.stokes_blocks(WL.tod_w0(s, d, True)).select("pix", *(x.alias(n) for n, x in zip(("k11", "k12", "k13", "k22", "k23", "k33"), X.inv3_sym(*_BD.split(", ")))))).select("pix", "k11", "k12", "k33"))
query("coadd_pol", f"WITH {O.W0P}, {O.BD3}, r AS (SELECT pix, sum(d) AS i, sum(d * cos(2 * phi)) AS q, sum(d * sin(2 * phi)) AS u FROM tod GROUP BY pix) SELECT pix, round(((c22*c33-c23*c23)*i + (c13*c23-c12*c33)*q + (c12*c23-c13*c22)*u)/{_DET}, 4) + 0.0 AS i FROM bl JOIN r USING (pix)")(lambda s, d: rounded(P.coadd(WL.tod_w0(s, d, True), 3), 4).select("pix", "i"))

# ---- coarse spaces ----


query("zs_intensity", f"WITH {O.W0}, {O.PZ} SELECT pix, interval_id AS col, round(z, 9) AS v FROM zs")(lambda s, d: P.coarse_columns(WL.tod_w0(s, d)).select("pix", "col", F.round("z", 9).alias("v")))
query("zs_merged_r10", f"WITH {O.W0}, {O.PZ}, k AS (SELECT max(interval_id) + 1 AS k FROM tod) SELECT pix, CAST(interval_id * 10 // k AS BIGINT) AS col, round(sum(z), 9) AS v FROM zs, k GROUP BY ALL")(lambda s, d: P.coarse_columns(tod := WL.tod_w0(s, d), 10, tod.agg(F.max("interval_id") + 1).first()[0]).select("pix", "col", F.round("z", 9).alias("v")))
query("zs_rowsum", f"WITH {O.W3}, {O.PZ} SELECT CAST(pix AS BIGINT) AS pix, round(sum(z), 9) AS v FROM zs GROUP BY pix")(lambda s, d: P.coarse_columns(WL.tod_w3(s, d)).groupBy("pix").agg(F.round(F.sum("z"), 9).alias("v")))


@query("zs_polarised", f"WITH {O.W0}, {O.PZ}, c AS (SELECT DISTINCT interval_id AS col FROM tod), p AS (SELECT DISTINCT pix FROM tod) SELECT p.pix, CAST(s AS INTEGER) AS stokes, CAST(c.col AS BIGINT) AS col, CASE WHEN s = 0 THEN round(coalesce(z, 0), 9) ELSE 0.0 END + 0.0 AS v FROM p, c, range(3) r(s) LEFT JOIN zs ON zs.pix = p.pix AND zs.interval_id = c.col")
def _(spark, d):
    """The a-priori space of a polarised system as the solver has it: zero in the rows of q and u."""
    op = Y.NormalOperator(WL.tod_w0(spark, d, True), model_w0(), 3)
    interval, hits = op.hits()
    z = precond.a_priori(hits, 3).reshape(len(op.pixels), 3, -1)
    op.close()
    return spark.createDataFrame([(int(p), k, int(c), float(z[i, k, j])) for i, p in enumerate(op.pixels) for k in range(3) for j, c in enumerate(interval)], "pix long, stokes int, col long, v double").select("pix", "stokes", "col", r6(F.col("v"), 9).alias("v"))


_AZ = f"{O.W0}, {O.KERN0}, {O.A0}, {O.PZ}, z5 AS (SELECT pix, interval_id * 5 // 30 AS c, sum(z) AS z FROM zs GROUP BY ALL), az AS (SELECT p AS pix, c, sum(v * z) AS v FROM am JOIN z5 ON z5.pix = am.q GROUP BY ALL)"


def _coarse5(spark, d):
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    z = precond.merge_columns(precond.a_priori(op.hits()[1]), 5)
    return op, precond.Coarse(z, op.apply_many(z, sparse=True))


@query("az_w0", f"WITH {_AZ} SELECT pix, CAST(c AS BIGINT) AS col, round(v, 6) + 0.0 AS v FROM az")
def _(spark, d):
    op, c = _coarse5(spark, d)
    return spark.createDataFrame([(int(p), j, float(c.az[i, j])) for i, p in enumerate(op.pixels) for j in range(5)], "pix long, col long, v double").select("pix", "col", r6(F.col("v")).alias("v"))


@query("coarse_e_w0", f"WITH {_AZ} SELECT CAST(z5.c AS BIGINT) AS i, CAST(az.c AS BIGINT) AS j, round(sum(z * v), 6) + 0.0 AS v FROM z5 JOIN az USING (pix) GROUP BY ALL")
def _(spark, d):
    _, c = _coarse5(spark, d)
    return spark.createDataFrame([(i, j, float(c.e[i, j])) for i in range(5) for j in range(5)], "i long, j long, v double").select("i", "j", r6(F.col("v")).alias("v"))


query("ones_image", f"WITH {O.W0}, {O.KERN0}, {O.A0} SELECT p AS pix, round(sum(v), 5) + 0.0 AS i FROM am GROUP BY p")(lambda s, d: rounded((op := Y.NormalOperator(WL.tod_w0(s, d), model_w0())).table(op.apply(np.ones(op.n))), 5))
_ZERO = f"WITH {O.W0} SELECT DISTINCT pix, CAST(c AS BIGINT) AS col, 0.0 AS v FROM tod, range(5) r(c)"


def _cells(spark, op, m):
    return spark.createDataFrame([(int(p), j, float(m[i, j])) for i, p in enumerate(op.pixels) for j in range(m.shape[1])], "pix long, col long, v double").select("pix", "col", r6(F.col("v")).alias("v"))


@query("deflation_raz_zero", _ZERO)
def _(spark, d):
    op, c = _coarse5(spark, d)
    return _cells(spark, op, precond.deflation(c)(c.az))


for _variant in ("def1",):
    @query(f"two_level_identity_{_variant}", f"WITH {_AZ} SELECT pix, CAST(c AS BIGINT) AS col, round(coalesce(z, 0), 6) + 0.0 AS v FROM (SELECT pix, c FROM (SELECT DISTINCT pix FROM tod), range(5) r(c)) LEFT JOIN z5 USING (pix, c)")
    def _(spark, d, variant=_variant):
        """The two-level preconditioner maps A Z to Z."""
        op, c = _coarse5(spark, d)
        f = precond.two_level(precond.BlockDiagonal(op.diagonal_blocks()), c, variant)
        return _cells(spark, op, np.stack([f(v) for v in c.az.T], axis=1))


# ---- measures and experiments ----

# with white weights the system is diagonal in the hits of its pixels, so that a day's condition number is their quotient
query("kappa_bound", f"WITH h AS (SELECT {O.DAY} AS interval_id, count(*) AS n FROM events GROUP BY {O.DAY}, user_id), k AS (SELECT interval_id, max(n) / CAST(min(n) AS DOUBLE) AS kappa FROM h GROUP BY 1) SELECT interval_id, kappa, j, round(2 * ((sqrt(kappa) - 1) / (sqrt(kappa) + 1))**j, 9) AS bound FROM k, range(0, 50, 5) r(j)")(lambda s, d: _kappa_bound(s, d))


def _kappa_bound(spark, d) -> DataFrame:
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("long")
    h = load(spark, d, "events").groupBy(day.alias("interval_id"), "user_id").agg(F.count("*").alias("n"))
    k = h.groupBy("interval_id").agg((F.max("n") / F.min("n")).alias("kappa"))
    return k.select("interval_id", "kappa", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(45).cast("long"), F.lit(5).cast("long"))).alias("j")).select("interval_id", "kappa", "j", F.round(X.cg_bound("kappa", "j"), 9).alias("bound"))


query("cost_model", f"WITH {O.W0}, n AS (SELECT interval_id, count(*) AS n FROM tod GROUP BY 1) SELECT round(sum(n * (1 + log2(128))), 3) AS banded, round(sum(n * (1 + log2(n))), 3) AS whole FROM n")(lambda s, d: P.operations(WL.tod_w0(s, d), 128).select(F.round("operations", 3).alias("banded")).join(P.operations(WL.tod_w0(s, d), None).select(F.round("operations", 3).alias("whole"))))
_REBIN = "SELECT n_regionkey, n_nationkey, round(sum(o_totalprice), 2) AS total, count(*) AS n FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey GROUP BY "


def _rebin(spark, d):
    n = load(spark, d, "nation").select("n_nationkey", "n_regionkey")
    return WL.tod_w6(spark, d).join(n, F.col("pix") == F.col("n_nationkey"))


query("map_rebin_rollup", _REBIN + "ROLLUP (n_regionkey, n_nationkey)")(lambda s, d: _rebin(s, d).rollup("n_regionkey", "n_nationkey").agg(*(F.round(F.sum("d"), 2).alias("total"), F.count("*").alias("n"))))
query("map_rebin_cube", _REBIN + "CUBE (n_regionkey, n_nationkey)")(lambda s, d: _rebin(s, d).cube("n_regionkey", "n_nationkey").agg(F.round(F.sum("d"), 2).alias("total"), F.count("*").alias("n")))


@query("map_rebin_grouping_sets", _REBIN + "GROUPING SETS ((n_regionkey), (n_nationkey), ())")
def _(spark, d):
    _rebin(spark, d).createOrReplaceTempView("_rebin")
    return spark.sql("SELECT n_regionkey, n_nationkey, round(sum(d), 2) AS total, count(*) AS n FROM _rebin GROUP BY GROUPING SETS ((n_regionkey), (n_nationkey), ())")


@query("map_full_outer_diff", f"WITH {O.W0}, a AS (SELECT pix, avg(d) AS v FROM tod WHERE interval_id < 2 GROUP BY pix), b AS (SELECT pix, avg(d) AS v FROM tod WHERE interval_id BETWEEN 2 AND 3 GROUP BY pix) SELECT coalesce(a.pix, b.pix) AS pix, round(coalesce(a.v, 0) - coalesce(b.v, 0), 5) + 0.0 AS diff FROM a FULL JOIN b ON a.pix = b.pix")
def _(spark, d):
    tod = WL.tod_w0(spark, d)
    a, b = (tod.where(F.col("interval_id").between(*r)).groupBy("pix").agg(F.avg("d").alias(n)) for r, n in (((0, 1), "a"), ((2, 3), "b")))
    return a.join(b, "pix", "full_outer").select("pix", r6(F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0)), 5).alias("diff"))


_TIMES = "prec string, coarse_dim int, iterations int, rel_residual double, true_residual double, build_s double, solve_s double"


def _table(spark, runs, extra: str = ""):
    return spark.createDataFrame([(*(x for x in key), r.prec, r.coarse_dim, r.solution.iterations, r.solution.history[-1][1], r.solution.true_residual, r.build_s, r.solve_s) for key, r in runs], extra + _TIMES)


def _both(op, n_max: int = 400, eps: float = 0.2, formed: bool = True, **apriori):
    """``formed``: products by the matrix where it fits, for sweeps; else every product is a pass over the blocks."""
    if formed:
        op.form()
    b = op.rhs()
    return [S.make_map(None, None, prec=p, op=op, b=b, max_iter=n_max, strict=False, eps_tol=eps, **(apriori if p == "apriori" else {})) for p in ("bd", "apriori", "aposteriori")]


@query("history_w0")
def _(spark, d):
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    out = [r.history() for r in _both(op, formed=False)]
    return out[0].unionByName(out[1]).unionByName(out[2])


#: Sub-sampled numbers of circles, those below the table's own number being further points of the sweep.
CIRCLES = (32, 64, 128, 256, 512, 1024, 2048)


def _convergence(spark, d, polarisers):
    """Iterations of the three preconditioners on big circles, by polariser and number of circles: all of the table first, then fewer."""
    runs = []
    model = K.Stationary({0: K.kernel(0.02, 256), 1: K.kernel(0.05, 256)})
    whole = load(spark, d, "supplier").count()
    for pol in polarisers:
        for n in (None, *(c for c in CIRCLES if c < whole)):
            tod = WL.tod_w3(spark, d, pol, n)
            s = 1 if pol == "none" else 3
            if s == 3:
                tod = P.pixel_cut(tod)[0]
            op = Y.NormalOperator(tod, model, s, SHORT)
            runs += [((pol, n or whole), r) for r in _both(op)]
            op.close()
    return _table(spark, runs, "polariser string, circles int, ")


query("convergence_by_circles")(lambda s, d: _convergence(s, d, ("none", "fast")))
query("convergence_medium")(lambda s, d: _convergence(s, d, ("medium",)))
query("convergence_slow")(lambda s, d: _convergence(s, d, ("slow",)))


#: Samples of a chunk where an interval is all of the scan, so that many tasks share it.
SHORT = 1 << 16


def _system(tod, model, nstokes: int = 1):
    """The operator of a sweep, whose many solves take their products from its matrix where that fits; else from passes over the blocks."""
    return Y.NormalOperator(tod, model, nstokes, SHORT).form()


def _knees(spark, tod):
    runs, models = [], {fk: K.Stationary({0: K.kernel(fk, 1024, grid_n=262144)}) for fk in (0.005, 0.02, 0.1)}
    packed = Y.NormalOperator(tod, models[0.1], 1, SHORT)
    for fk, model in models.items():
        runs += [((fk,), r) for r in _both(packed.other(model), eps=0.3)]
    packed.close()
    return _table(spark, runs, "fknee double, ")


query("knee_sweep_w1")(lambda s, d: _knees(s, WL.tod_w1(s, d)))
query("knee_sweep_w2")(lambda s, d: _knees(s, WL.tod_w2(s, d)))


def _ranks(spark, tod, nstokes):
    """Columns of the a-priori space, all intervals first, then ever fewer."""
    op = _system(tod, K.Stationary({0: K.kernel(0.02, 256), 1: K.kernel(0.05, 256)}), nstokes)
    b, k = op.rhs(), len(op.intervals())
    runs = [((0,), S.make_map(None, None, op=op, b=b, strict=False, max_iter=300))]
    runs += [((r,), S.make_map(None, None, prec="apriori", rank=r, op=op, b=b, strict=False, max_iter=300)) for r in dict.fromkeys((k, min(k, 50), min(k, 10), 1))]
    op.close()
    return _table(spark, runs, "rank int, ")


query("coarse_rank_apriori_w3")(lambda s, d: _ranks(s, WL.tod_w3(s, d), 1))
query("coarse_rank_apriori_medium_w3")(lambda s, d: _ranks(s, P.pixel_cut(WL.tod_w3(s, d, "medium"))[0], 3))


def _thresholds(spark, tod):
    op = _system(tod, K.Stationary({0: K.kernel(0.02, 256)}))
    b = op.rhs()
    runs = [((0.0,), S.make_map(None, None, op=op, b=b, strict=False, max_iter=400))]
    runs += [((e,), S.make_map(None, None, prec="aposteriori", eps_tol=e, op=op, b=b, strict=False, max_iter=400)) for e in (0.05, 0.1, 0.2, 0.3, 0.5)]
    op.close()
    return _table(spark, runs, "eps double, ")


query("coarse_rank_aposteriori_w2")(lambda s, d: _thresholds(s, WL.tod_w2(s, d, intervals="circle")))
query("coarse_rank_aposteriori_whole_w2")(lambda s, d: _thresholds(s, WL.tod_w2(s, d)))


@query("band_sweep_w2")
def _(spark, d):
    """All three preconditioners over the band's width, to the widest that the whole scan of the smallest table has."""
    runs, models = [], {lam: K.Stationary({0: K.kernel(0.1, lam, grid_n=65536)}) for lam in (32, 128, 1024, 8192)}
    packed = Y.NormalOperator(WL.tod_w2(spark, d), models[8192], 1, SHORT)
    for lam, model in models.items():
        runs += [((lam,), r) for r in _both(packed.other(model), eps=0.3)]
    packed.close()
    return _table(spark, runs, "band int, ")


@query("variants_w0")
def _(spark, d):
    """Both two-level forms on one coarse space: iterations and coarse solves."""
    rows = []
    for name, tod, model in (("w0", WL.tod_w0(spark, d), model_w0()), ("w2", WL.tod_w2(spark, d, intervals="circle"), K.Stationary({0: K.kernel(0.02, 256)}))):
        op = Y.NormalOperator(tod, model)
        b = op.rhs()
        for v, solves in (("def1", 1), ("def2", 2)):
            r = S.make_map(None, None, prec="apriori", variant=v, op=op, b=b, strict=False)
            rows.append((name, v, r.solution.iterations, solves * r.solution.iterations, r.solution.true_residual, r.solve_s))
        op.close()
    return spark.createDataFrame(rows, "workload string, variant string, iterations int, coarse_solves int, true_residual double, solve_s double")


def _scaling(spark, d, weak: bool):
    model = K.Stationary({0: K.kernel(0.02, 256), 1: K.kernel(0.05, 256)})
    cores, whole = spark.sparkContext.defaultParallelism, load(spark, d, "supplier").count()
    tasks = [t for t in (1, 2, 4, 8, 16, 32) if t <= cores]
    circles = [max(1, whole * t // tasks[-1]) if weak else whole for t in tasks]
    rows = S.scalings(spark, lambda n: WL.tod_w3(spark, d, "none", None if n == whole else n), model, circles, tasks, {"bd": {}, "apriori": {"rank": 10}, "aposteriori": {"eps_tol": 0.2}})
    return spark.createDataFrame(rows, "prec string, circles int, tasks int, samples long, iterations int, build_s double, solve_s double, iteration_s double")


query("weak_scaling_w3")(lambda s, d: _scaling(s, d, True))
query("strong_scaling_w3")(lambda s, d: _scaling(s, d, False))


@query("spectrum_w0")
def _(spark, d):
    """Ends of the spectra of A, BD A and both two-level forms, with condition numbers."""
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    a = S.dense(op)
    bd = precond.BlockDiagonal(op.diagonal_blocks())
    z = precond.a_priori(op.hits()[1])
    c = precond.Coarse(z, a @ z)
    rows, forms = [], {"A": None, "BD": bd, "2L_def1": precond.two_level(bd, c), "2L_def2": precond.two_level(bd, c, "def2")}
    for name, v in zip(forms, S.spectra(a, list(forms.values()))):
        rows += [(name, i, float(x), S.condition_number(v)) for i, x in [*enumerate(v[:20]), *list(enumerate(v))[-20:]]]
    op.close()
    return spark.createDataFrame(rows, "prec string, rank int, lambda double, kappa double")


@query("ritz_w0")
def _(spark, d):
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    bd = precond.BlockDiagonal(op.diagonal_blocks())
    _, w, h = krylov.gmres(op.apply, bd, op.rhs(), 1e-8, 100)
    r = krylov.ritz(w, h)
    s = krylov.cg(op.apply, bd, op.rhs(), tol=1e-8, keep_basis=True)
    c = krylov.ritz_from_cg(s)
    return spark.createDataFrame([("arnoldi", i, float(v.real), float(e)) for i, (v, e) in enumerate(zip(r.values, r.error))] + [("cg", i, float(v), float(e)) for i, (v, e) in enumerate(zip(c.values, c.error))], "source string, rank int, value double, error double")


@query("speedups_w3")
def _(spark, d):
    op = Y.NormalOperator(WL.unplaced_w3(spark, d), K.Stationary({0: K.kernel(0.02, 256), 1: K.kernel(0.05, 256)}), 1)
    runs = _both(op, formed=False)
    op.close()
    return spark.createDataFrame([(r.prec, n, *map(float, S.speedups(runs[0], r, n).values())) for r in runs[1:] for n in (1, 10, 100)], "prec string, n_rhs int, speedup_solve double, speedup_total double, speedup_amortised double, speedup_iterations double")


@query("breakdown_w3")
def _(spark, d):
    op = Y.NormalOperator(WL.tod_w3(spark, d), K.Stationary({0: K.kernel(0.02, 256), 1: K.kernel(0.05, 256)}), 1)
    m, c = S.build(op, "apriori", 10)
    t = S.breakdown(op, c, precond.BlockDiagonal(op.diagonal_blocks()))
    return spark.createDataFrame([(k, float(v)) for k, v in t.items()], "step string, seconds double")


@query("many_rhs_w0")
def _(spark, d):
    """Eight noise realisations in one batched solve."""
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    m, _ = S.build(op, "apriori", 10)
    bs = op.apply_many(np.random.default_rng(3).standard_normal((op.n, 8)))
    _, took = S.solve_many(op, m, bs)
    return spark.createDataFrame([(i, int(n)) for i, n in enumerate(took)], "rhs int, iterations int")


KNEES = {0: 0.05, 1: 0.1}


def _quality(spark, tod, knees, bands, realisations=3, grid=(32, 64)):
    """(method, band, rms, bias, variance) of maps of a Gaussian sky with noise of the spectrum that the weights model, over realisations."""
    pix = P.pointed(tod).select("pix").distinct()
    sky = cut(pix.select("pix", SIM.gaussian_sky(F.col("pix"), *grid, amplitude=3.0).alias("i")))
    truth = np.array([r["i"] for r in sky.orderBy("pix").collect()])
    out: dict = {}
    for seed in range(realisations):
        sim = cut(SIM.make_tod(tod, sky, 1, knees, seed=10 * seed + 1))
        for lam in bands:
            r = S.make_map(sim, K.Stationary({k: K.kernel(f, lam) for k, f in knees.items()}), strict=False, max_iter=300)
            out.setdefault((f"band_{lam}", lam), []).append(r.solution.x)
            r.op.close()
        out.setdefault(("coadd", 0), []).append(P.coadd(sim).orderBy("pix").toArrow().column("i").to_numpy())
    rows = []
    for (name, lam), maps in out.items():
        m = np.stack(maps, axis=1) - truth[:, None]
        m = m - m.mean(axis=0)  # the offset is not determined
        rows.append((name, lam, float(np.sqrt((m**2).mean())), float(m.mean(axis=1).std()), float(S.variance_by_pixel(m).mean())))
    return rows


@query("map_quality_by_band")
def _(spark, d):
    return spark.createDataFrame(_quality(spark, WL.tod_w0(spark, d), KNEES, (4, 16, 64, 128)), "method string, band int, rms double, systematic double, variance double")


@query("map_quality_w2")
def _(spark, d):
    return spark.createDataFrame(_quality(spark, WL.tod_w2(spark, d), {0: 0.05}, (16, 128, 512), 1, (64, 128)), "method string, band int, rms double, systematic double, variance double")


@query("template_marginalised_w0")
def _(spark, d):
    """Offsets and slopes of every interval projected out of the weights."""
    def templates(n):
        return np.stack((np.ones(n), np.linspace(-1, 1, n)))

    tod = WL.tod_w0(spark, d).withColumn("d", WL.sky(F.col("pix")) + 50 * F.col("interval_id") + 0.1 * F.col("t"))
    r = S.make_map(tod, K.TemplateMarginalised(model_w0(), templates), strict=False, max_iter=200)
    truth = 10 + 3 * np.sin(r.op.pixels * 0.37) + 2 * np.cos(r.op.pixels * 0.11)
    return spark.createDataFrame([(S.map_rms(r.solution.x, truth), r.solution.iterations)], "rms double, iterations int")


def cut_model(f_cut: float):
    """Weights without the modes below a cut. A Gaussian window that ends at the band leaves such weights negative at the lowest
    modes, which intervals of some thousand samples have; the triangle does not."""
    return K.Stationary({k: K.kernel(f, 128, f_cut=f_cut, kind="triangle" if f_cut else "gauss") for k, f in KNEES.items()})


@query("mode_filter_w0")
def _(spark, d):
    """Modes below a cut dropped in A and b alike leave a noise-free sky unbiased up to its offset; dropped in the data alone they bias it."""
    tod = WL.tod_w0(spark, d).withColumn("d", WL.sky(F.col("pix")))
    cuts, both, bs = (0.0, 0.01, 0.05), [], []
    full = _system(tod, model_w0())
    truth = 10 + 3 * np.sin(full.pixels * 0.37) + 2 * np.cos(full.pixels * 0.11)
    for f_cut in cuts:
        r = S.make_map(None, None, op=_system(tod, cut_model(f_cut)), strict=False, max_iter=200)
        both.append((S.map_rms(r.solution.x, truth), r.solution.iterations))
        bs.append(r.op.rhs())
        r.op.close()
    # the three sides of the one unfiltered system together
    x, took = S.solve_many(full, precond.BlockDiagonal(full.diagonal_blocks()), np.stack(bs, axis=1), max_iter=200)
    full.close()
    rows = [row for k, f_cut in enumerate(cuts) for row in (("both", f_cut, *both[k]), ("data_only", f_cut, S.map_rms(x[:, k], truth), int(took[k])))]
    return spark.createDataFrame(rows, "filtered string, f_cut double, rms double, iterations int")


@query("refreshed_space_w0")
def _(spark, d):
    """A coarse space joined over three runs: its size and the iterations of the next solve."""
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    bd, b, rows = precond.BlockDiagonal(op.diagonal_blocks()), op.rhs(), []
    z = np.empty((op.n, 0))
    for k in range(3):
        _, w, h = krylov.gmres(op.apply, bd, np.random.default_rng(k).standard_normal(op.n), 1e-6, 100)
        z = precond.update(z, op.apply, bd, krylov.ritz(w, h), 0.3, 12)
        s = krylov.cg(op.apply, precond.two_level(bd, precond.Coarse(z, op.apply_many(z))), b, strict=False)
        rows.append((k, z.shape[1], s.iterations, s.true_residual))
    op.close()
    return spark.createDataFrame(rows, "run int, dim int, iterations int, true_residual double")


# ---- what must hold, as rows that SQL can state ----


def holds(name: str, *facts: str):
    """A query of (fact, ok) rows; its SQL says that each holds."""
    return query(name, "SELECT * FROM (VALUES " + ", ".join(f"('{f}', true)" for f in facts) + ") v(fact, ok)")


def _facts(spark, **facts) -> DataFrame:
    return spark.createDataFrame([(k, bool(v)) for k, v in facts.items()], "fact string, ok boolean")


def _w0_system(spark, d):
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    return op, op.rhs(), precond.BlockDiagonal(op.diagonal_blocks())


@holds("history_holds_w0", "from_one", "to_tolerance", "true_residual_agrees", "apriori_not_more", "aposteriori_not_more", "gain_is_quotient", "iterations_to_is_last", "plateau_within_run")
def _(spark, d):
    op = Y.NormalOperator(WL.tod_w0(spark, d), model_w0())
    runs = _both(op, formed=False)
    h = [r.solution.history for r in runs]
    n = [r.solution.iterations for r in runs]
    op.close()
    return _facts(spark, from_one=all(x[0][1] == 1 for x in h), to_tolerance=all(x[-1][1] <= 1e-6 < x[-2][1] for x in h), true_residual_agrees=all(abs(r.solution.true_residual - r.solution.history[-1][1]) < 1e-9 for r in runs), apriori_not_more=n[1] <= n[0], aposteriori_not_more=n[2] <= n[0], gain_is_quotient=S.iteration_gain(runs[0], runs[2]) == n[0] / n[2], iterations_to_is_last=all(S.iterations_to(x, 1e-6) == k for x, k in zip(h, n)), plateau_within_run=all(0 <= S.plateau(x) <= k for x, k in zip(h, n)))


@holds("krylov_holds_w0", "basis_orthonormal", "arnoldi_relation", "gmres_tolerance", "ritz_residuals", "cg_ritz_in_spectrum", "az_without_a_pass", "selection_below_threshold")
def _(spark, d):
    op, b, bd = _w0_system(spark, d)
    a = S.dense(op)
    m = lambda v: bd(a @ v)
    w, h = krylov.arnoldi(m, b, 12)
    k = h.shape[1]
    r = krylov.ritz(w, h)
    g = krylov.gmres(op.apply, bd, b, 1e-8, 100)[0]
    c = krylov.ritz_from_cg(krylov.cg(op.apply, bd, b, tol=1e-8, keep_basis=True))
    v = S.spectrum(a, bd)
    real = np.abs(r.values.imag) < 1e-12
    left = np.linalg.norm(m(r.vectors[:, real].real) - r.vectors[:, real].real * r.values[real].real, axis=0)
    az = precond.az_from_arnoldi(precond.BlockDiagonal(bd.inverse), w, h, np.eye(k))
    z = precond.select(r, dim=4)
    out = _facts(spark, basis_orthonormal=np.allclose(w.T @ w, np.eye(w.shape[1])), arnoldi_relation=np.allclose(m(w[:, :k]), w[:, : h.shape[0]] @ h), gmres_tolerance=g.converged and g.history[-1][1] <= 1e-8, ritz_residuals=np.allclose(left, r.error[real], atol=1e-8), cg_ritz_in_spectrum=c.values.min() >= v.min() - 1e-8 and c.values.max() <= v.max() + 1e-8, az_without_a_pass=np.allclose(az, a @ w[:, :k]), selection_below_threshold=z.shape[1] >= 4 and np.allclose(z.T @ z, np.eye(z.shape[1])))
    op.close()
    return out


@holds("spectrum_holds_w0", "a_positive", "kappa_falls", "forms_share_spectrum", "coarse_values_at_one", "bound_on_error", "standard_near_one")
def _(spark, d):
    op, b, bd = _w0_system(spark, d)
    a = S.dense(op)
    c = precond.Coarse(z := precond.a_priori(op.hits()[1]), a @ z)
    va, vb, v1, v2 = S.spectra(a, [None, bd, *(precond.two_level(bd, c, k) for k in ("def1", "def2"))])
    ka, kb, k1 = map(S.condition_number, (va, vb, v1))
    ref, kappa = S.solved(a, b), kb
    x = [krylov.cg(lambda v: a @ v, bd, b, tol=0, max_iter=j, strict=False).x for j in (2, 5, 8)]
    e = [S.a_norm_error(a, y, ref) for y in x]
    rate = (math.sqrt(kappa) - 1) / (math.sqrt(kappa) + 1)
    out = _facts(spark, a_positive=va.min() > 0, kappa_falls=k1 < kb <= ka, forms_share_spectrum=np.allclose(v1, v2, atol=1e-7), coarse_values_at_one=(np.abs(v1 - 1) < 1e-7).sum() >= z.shape[1] - c.rank_dropped, bound_on_error=all(y <= 2 * rate**j * S.a_norm_error(a, 0 * ref, ref) * 1.0001 for y, j in zip(e, (2, 5, 8))), standard_near_one=(np.abs(vb - 1) < 0.5).mean() > 0.5)
    op.close()
    return out


@holds("many_rhs_holds_w0", "equal_to_single", "one_build_serves_all", "amortised_grows")
def _(spark, d):
    op, b, bd = _w0_system(spark, d)
    m, c = S.build(op, "apriori", 10)
    bs = op.apply_many(np.random.default_rng(3).standard_normal((op.n, 4)))
    xs, took = S.solve_many(op, m, bs, 1e-10)
    one = [krylov.cg(op.apply, m, bs[:, k], tol=1e-10) for k in range(4)]
    runs = [S.Run("bd", one[0], 0, 1.0, 10.0, op), S.Run("apriori", one[1], 10, 4.0, 5.0, op)]
    by = [S.speedups(*runs, n) for n in (1, 10, 100)]
    op.close()
    return _facts(spark, equal_to_single=all(np.allclose(xs[:, k], one[k].x, atol=1e-6) for k in range(4)), one_build_serves_all=all(abs(t - s.iterations) <= 1 for t, s in zip(took, one)), amortised_grows=by[0]["speedup_total"] == by[0]["speedup_amortised"] < by[1]["speedup_amortised"] < by[2]["speedup_amortised"] < by[0]["speedup_solve"])


@holds("variants_hold_w0", "same_map", "start_has_coarse_part", "similar_iterations", "refreshed_space_helps")
def _(spark, d):
    op, b, bd = _w0_system(spark, d)
    r = [S.make_map(None, None, prec="apriori", rank=10, variant=v, op=op, b=b, tol=1e-10) for v in ("def1", "def2")]
    x0 = precond.def2_start(b, r[1].coarse)
    plain = krylov.cg(op.apply, bd, b).iterations
    z = np.empty((op.n, 0))
    for k in range(2):
        _, w, h = krylov.gmres(op.apply, bd, np.random.default_rng(k).standard_normal(op.n), 1e-6, 100)
        z = precond.update(z, op.apply, bd, krylov.ritz(w, h), 0.3, 12)
    fresh = krylov.cg(op.apply, precond.two_level(bd, precond.Coarse(z, op.apply_many(z))), b).iterations
    out = _facts(spark, same_map=np.allclose(r[0].solution.x, r[1].solution.x, atol=1e-6), start_has_coarse_part=np.allclose(r[1].coarse.z.T @ (b - op.apply(x0)), 0, atol=1e-7), similar_iterations=abs(r[0].solution.iterations - r[1].solution.iterations) <= 3, refreshed_space_helps=fresh <= plain and z.shape[1] <= 12)
    op.close()
    return out


def same_noise(one: DataFrame, two: DataFrame) -> bool:
    """Whether two streams have the same samples, compared where they are: none of them comes to the driver."""
    both = one.join(two.withColumnRenamed("n", "m"), ["interval_id", "t"], "full")
    near = F.coalesce(F.abs(F.col("n") - F.col("m")) <= 1e-9 + 1e-5 * F.abs("m"), F.lit(False))
    return bool(both.agg(F.min(near)).first()[0])


@holds("simulation_holds", "same_under_partitions", "spectrum_matches", "sky_is_the_same", "noise_free_is_exact", "wider_band_is_better", "weights_beat_coadd")
def _(spark, d):
    tod = WL.tod_w0(spark, d)
    same = same_noise(*(SIM.noise(t, KNEES, length=n) for t, n in ((tod, 1 << 20), (tod.repartition(3, "t"), 100))))
    # a long interval's averaged periodogram against P(f)
    line = spark.range(1 << 16).select(F.lit(0).cast("long").alias("interval_id"), F.col("id").alias("t"), F.lit(0).alias("noise_id"))
    y = np.array([r["n"] for r in SIM.noise(line, {0: 0.05}).orderBy("t").select("n").collect()]).reshape(-1, 1024)
    p = (np.abs(np.fft.rfft(y * np.hanning(1024), axis=1)) ** 2).mean(axis=0) / (np.hanning(1024) ** 2).sum()
    f = np.arange(513) / 1024
    band = slice(16, 500)
    want = 1 + (0.05 / f[band]) ** 2
    rows = {r[0]: r[2] for r in _quality(spark, tod, KNEES, (4, 64), 2)}
    sky = [cut(tod.select("pix").distinct().repartition(k).select("pix", SIM.gaussian_sky(F.col("pix"), 32, 64).alias("i"))).orderBy("pix").toPandas().i.to_numpy() for k in (1, 5)]
    free = SIM.make_tod(tod, tod.select("pix").distinct().withColumn("i", WL.sky(F.col("pix"))))
    exact = S.make_map(free, model_w0(), tol=1e-12)
    truth = 10 + 3 * np.sin(exact.op.pixels * 0.37) + 2 * np.cos(exact.op.pixels * 0.11)
    return _facts(spark, same_under_partitions=same, spectrum_matches=abs(np.mean(p[band] / want) - 1) < 0.05 and np.abs(np.log(p[band] / want)).mean() < 0.2, sky_is_the_same=np.allclose(*sky), noise_free_is_exact=np.allclose(exact.solution.x, truth, atol=1e-6), wider_band_is_better=rows["band_64"] < rows["band_4"], weights_beat_coadd=rows["band_64"] < rows["coadd"])


@holds("filters_hold_w0", "consistent_is_unbiased", "data_only_is_biased", "templates_are_removed", "hits_split_exactly", "growing_window_rejected")
def _(spark, d):
    tod = WL.tod_w0(spark, d).withColumn("d", WL.sky(F.col("pix")))
    r = S.make_map(None, None, op=_system(tod, cut_model(0.05)), strict=False, max_iter=300, tol=1e-9)
    truth = 10 + 3 * np.sin(r.op.pixels * 0.37) + 2 * np.cos(r.op.pixels * 0.11)
    biased = S.make_map(None, None, op=_system(tod, model_w0()), b=r.op.rhs(), strict=False, max_iter=300)
    line = lambda n: np.stack((np.ones(n), np.linspace(-1, 1, n)))
    t = S.make_map(None, None, op=_system(tod.withColumn("d", F.col("d") + 50 * F.col("interval_id") + 0.1 * F.col("t")), K.TemplateMarginalised(model_w0(), line)), strict=False, max_iter=300, tol=1e-9)
    split = Y.NormalOperator(tod, model_w0(), length=100)
    try:
        K.check_positive(K.kernel(0.02, 100, kind="cut") * np.exp(2 * (np.arange(101) / 100) ** 2))
        rejected = False
    except ValueError:
        rejected = True
    same = np.array_equal(split.hits()[1], r.op.hits()[1])
    return _facts(spark, consistent_is_unbiased=S.map_rms(r.solution.x, truth) < 1e-4, data_only_is_biased=S.map_rms(biased.solution.x, truth) > 1e-2, templates_are_removed=S.map_rms(t.solution.x, truth) < 1e-3, hits_split_exactly=same, growing_window_rejected=rejected)


# ---- generated scans and table-valued functions ----

_SCAN = f"SELECT o_orderkey, o_custkey % 7 AS interval_id, {O.circle('(dayofyear(o_orderdate) * (2 * pi() / 366))', '((o_custkey % 7) * (2 * pi() / 7))', 30.0, 32, 64)} AS pix FROM orders"


@query("scan_source", _SCAN)
def _(spark, d):
    """The generated scan's pixels for the days of the orders on seven circles."""
    o = load(spark, d, "orders").select("o_orderkey", (F.col("o_custkey") % 7).cast("long").alias("interval_id"), F.dayofyear("o_orderdate").alias("doy"))

    def run(batches):
        for b in batches:
            circle, doy = b.column(1).to_numpy(), b.column(2).to_numpy()
            pix = pixels(doy * (2 * math.pi / 366), circle * (2 * math.pi / 7), 30.0, 32, 64)
            yield pa.record_batch([b.column(0), b.column(1), pa.array(pix, pa.int64())], names=["o_orderkey", "interval_id", "pix"])

    return o.mapInArrow(run, "o_orderkey long, interval_id long, pix long")


@query("udtf_kernel_lags", f"WITH {O.DAYS}, {O.KERN0} SELECT interval_id, lag, round(w, 9) + 0.0 AS w FROM days JOIN kern ON kern.noise_id = interval_id % 2")
def _(spark, d):
    tables.register(spark)
    days(spark, d).withColumn("fknee", F.when(F.col("noise_id") == 0, 0.05).otherwise(0.1)).createOrReplaceTempView("_noise")
    return spark.sql("SELECT interval_id, lag, round(w, 9) + 0.0D AS w FROM _noise, LATERAL kernel_lags(fknee, 1.0D, 128, 1024)")


@query("udtf_small_map_w4", O.small_map(O.W4, 0.1, 8))
def _(spark, d):
    return rounded(tables.small_map(WL.tod_w4(spark, d).asTable().withSinglePartition(), F.lit(0.1), F.lit(8)))


query("stream_hitmap", "SELECT user_id AS pix, count(*) AS hits FROM events GROUP BY user_id")(lambda s, d: _streams().hit_map(s, d))
query("stream_coadd", "SELECT user_id AS pix, count(*) AS hits, round(avg(value), 4) + 0.0 AS i FROM events GROUP BY user_id")(lambda s, d: _streams().coadd(s, d))
query("stream_daily", "SELECT date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS day, count(*) AS n FROM events GROUP BY 1")(lambda s, d: _streams().daily(s, d))


query("stream_sessions", """WITH a AS (SELECT user_id AS pix, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS first FROM events),
b AS (SELECT pix, ts, sum(first) OVER (PARTITION BY pix ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM a)
SELECT pix, epoch_us(min(ts)) AS start_us, count(*) AS n FROM b GROUP BY pix, k HAVING max(ts) + INTERVAL 3 HOUR <= (SELECT max(ts) FROM events)""")(lambda s, d: _streams().sessions(s, d))
query("stream_interval_close", """SELECT date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS day, count(*) AS n, round(sum(value), 4) + 0.0 AS s FROM events GROUP BY 1
HAVING CAST(max(CAST(ts AS DATE)) AS TIMESTAMP) + INTERVAL 25 HOUR <= (SELECT max(ts) FROM events)""")(lambda s, d: _streams().interval_close(s, d))
query("stream_unique_hits", "SELECT user_id AS pix, count(*) AS hits FROM events GROUP BY user_id")(lambda s, d: _streams().unique_hits(s, d))
query("stream_near_pointing", "SELECT a.event_id AS sample_id, b.event_id AS pointing_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts BETWEEN a.ts - INTERVAL 10 MINUTE AND a.ts + INTERVAL 10 MINUTE")(lambda s, d: _streams().near_pairs(s, d))


def _streams():
    from skyweave.streaming import maps

    return maps


def queries() -> dict:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
