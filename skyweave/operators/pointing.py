"""Sample-to-pixel operators: expand, accumulate, hits, pixel cut, nearest earlier pointing, scan statistics."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from skyweave.functions.expr import inv3_sym, rcond3_sym, stokes_weights
from skyweave.sources.tables import require_columns


def expand(tod: DataFrame, sky: DataFrame, nstokes: int = 1, strategy: str = "shuffle") -> DataFrame:
    """y = P x: adds column y from a wide map (pix, i[, q, u]). ``broadcast`` is for maps whose size was checked."""
    m = F.broadcast(sky) if strategy == "broadcast" else sky
    y = F.col("i") if nstokes == 1 else F.col("i") + F.col("q") * F.cos(2 * F.col("phi")) + F.col("u") * F.sin(2 * F.col("phi"))
    return tod.join(m, "pix").withColumn("y", y).drop("i", "q", "u")


def accumulate(tod: DataFrame, y: str | Column = "y", nstokes: int = 1) -> DataFrame:
    """P' y as a wide map; partial sums are made before the shuffle."""
    v = F.col(y) if isinstance(y, str) else y
    sums = [F.sum(v).alias("i")]
    if nstokes == 3:
        sums += [F.sum(v * F.cos(2 * F.col("phi"))).alias("q"), F.sum(v * F.sin(2 * F.col("phi"))).alias("u")]
    return pointed(require_columns(tod, "pix", "phi")).groupBy("pix").agg(*sums)


def hit_map(tod: DataFrame) -> DataFrame:
    return pointed(tod).groupBy("pix").agg(F.count("*").alias("hits"))


def hits_by_interval(tod: DataFrame) -> DataFrame:
    return pointed(tod).groupBy("pix", "interval_id").agg(F.count("*").alias("hits"))


def stokes_blocks(tod: DataFrame, weight: Column | float = 1.0) -> DataFrame:
    """Upper triangle of P' diag(weight) P per pixel."""
    w = weight if isinstance(weight, Column) else F.lit(float(weight))
    c, s = F.cos(2 * F.col("phi")), F.sin(2 * F.col("phi"))
    cells = {"c11": w, "c12": w * c, "c13": w * s, "c22": w * c * c, "c23": w * c * s, "c33": w * s * s}
    return pointed(tod).groupBy("pix").agg(*(F.sum(v).alias(k) for k, v in cells.items()))


def condition(tod: DataFrame, nstokes: int = 3) -> DataFrame:
    """(pix, rcond) of every pixel's Stokes block."""
    if nstokes == 1:
        return hit_map(tod).select("pix", F.lit(1.0).alias("rcond"))
    return stokes_blocks(tod).select("pix", rcond3_sym("c11", "c12", "c13", "c22", "c23", "c33").alias("rcond"))


def pointed(tod: DataFrame) -> DataFrame:
    """Samples that see a pixel; slots left by a cut have pix -1."""
    return tod.where("pix >= 0")


def pixel_cut(tod: DataFrame, nstokes: int = 3, rcond: float = 1e-6, gap: str = "mask") -> tuple[DataFrame, DataFrame]:
    """(samples without those of badly conditioned pixels, the dropped pixels).

    The weights of a stationary interval depend on true lags, so a cut sample keeps its slot: ``mask`` leaves it with pix -1 and no data, and P is zero
    there. ``split`` drops it and makes every run between gaps an interval of its own. ``close`` moves later samples up, which changes their lags."""
    cond = condition(tod, nstokes)
    gone = cond.where(F.col("rcond") <= rcond).select("pix")
    if gap == "mask":
        cut = F.col("_cut").isNotNull()
        marked = tod.join(gone.withColumn("_cut", F.lit(True)), "pix", "left")
        return marked.withColumns({"pix": F.when(cut, F.lit(-1).cast("long")).otherwise(F.col("pix")), "d": F.when(cut, 0.0).otherwise(F.col("d"))}).drop("_cut"), gone
    kept = tod.join(gone, "pix", "left_anti")
    if gap == "split":
        return split_intervals(kept), gone
    if gap == "close":
        return reindex(kept), gone
    raise ValueError(f"unknown gap policy {gap!r}")


def reindex(tod: DataFrame) -> DataFrame:
    """Close the gaps in t within every interval."""
    return tod.withColumn("t", (F.row_number().over(W.partitionBy("interval_id").orderBy("t")) - 1).cast("long"))


def split_intervals(tod: DataFrame) -> DataFrame:
    """Runs of consecutive t as intervals of their own, numbered by (interval_id, first t); t starts from 0 in each."""
    w = W.partitionBy("interval_id").orderBy("t")
    new = F.coalesce(F.col("t") - F.lag("t").over(w) != 1, F.lit(True))
    runs = tod.withColumn("_t0", F.last(F.when(new, F.col("t")), ignorenulls=True).over(w))
    first = runs.select("interval_id", "_t0").distinct()
    from skyweave.plans.lineage import global_index

    ids = global_index(first, ["interval_id", "_t0"], "_new")
    return runs.join(ids, ["interval_id", "_t0"]).withColumns({"interval_id": F.col("_new"), "t": F.col("t") - F.col("_t0")}).drop("_t0", "_new")


def fill_gaps(tod: DataFrame) -> DataFrame:
    """Slots (pix -1, no data) for the values of t that an interval lacks between its first and last; t starts from 0 then."""
    w = W.partitionBy("interval_id").orderBy("t")
    lacking = tod.select("interval_id", "noise_id", "t", F.lag("t").over(w).alias("_p")).where("t - _p > 1")
    slots = lacking.select("interval_id", F.explode(F.sequence(F.col("_p") + 1, F.col("t") - 1)).alias("t"), "noise_id")
    slots = slots.select("interval_id", "t", F.lit(-1).cast("long").alias("pix"), F.lit(0.0).alias("phi"), F.lit(0.0).alias("d"), "noise_id")
    first = tod.groupBy("interval_id").agg(F.min("t").alias("_first"))
    both = tod.select(*slots.columns).unionByName(slots).join(first, "interval_id")
    return both.withColumn("t", F.col("t") - F.col("_first")).drop("_first")


def attach_asof(samples: DataFrame, pointing: DataFrame, key: str, time: str, values: list[str]) -> DataFrame:
    """The latest earlier (or simultaneous) pointing row of the same key for every sample: a union and one window, no range join."""
    null = [F.lit(None).cast(pointing.schema[v].dataType).alias(v) for v in values]
    rest = [c for c in samples.columns if c not in (key, time)]
    a = pointing.select(key, time, F.lit(0).alias("_side"), *values, *(F.lit(None).cast(samples.schema[c].dataType).alias(f"_s_{c}") for c in rest))
    b = samples.select(key, time, F.lit(1).alias("_side"), *null, *(F.col(c).alias(f"_s_{c}") for c in rest))
    w = W.partitionBy(key).orderBy(time, "_side").rowsBetween(W.unboundedPreceding, W.currentRow)
    both = a.unionByName(b)
    return both.select(key, time, "_side", *(F.last(v, ignorenulls=True).over(w).alias(v) for v in values), *(F.col(f"_s_{c}").alias(c) for c in rest)).where("_side = 1").drop("_side")


def interval_assign(samples: DataFrame, pieces: DataFrame, time: str, width: int) -> DataFrame:
    """Range join of samples to pieces (interval_id, lo, hi) by buckets of ``width``: equi-join, then a residual test."""
    p = pieces.withColumn("_b", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    return samples.withColumn("_b", F.floor(F.col(time) / width)).join(p, "_b").where(F.col(time).between(F.col("lo"), F.col("hi"))).drop("_b", "lo", "hi")


def band_pairs(tod: DataFrame, lambda_: int) -> DataFrame:
    """Pairs of samples of one interval at most ``lambda_`` apart (pix, pix2, lag): buckets of the band's width and their
    neighbours, an equi-join and a residual test."""
    width = max(1, lambda_)
    a = tod.select("interval_id", F.col("t"), F.col("pix"), F.explode(F.sequence(F.floor(F.col("t") / width) - 1, F.floor(F.col("t") / width) + 1)).alias("_b"))
    b = tod.select("interval_id", F.col("t").alias("t2"), F.col("pix").alias("pix2"), F.floor(F.col("t") / width).alias("_b"))
    return a.join(b, ["interval_id", "_b"]).where(F.abs(F.col("t") - F.col("t2")) <= lambda_).select("interval_id", "t", "t2", "pix", "pix2", F.abs(F.col("t") - F.col("t2")).alias("lag"))


def multiplicity(tod: DataFrame) -> DataFrame:
    """In how many intervals each pixel is seen."""
    return pointed(tod).select("pix", "interval_id").distinct().groupBy("pix").agg(F.count("*").alias("mult"))


def overlap(tod: DataFrame, a: int, b: int) -> DataFrame:
    """Pixels that two intervals share."""
    return tod.where(F.col("interval_id") == a).select("pix").intersect(tod.where(F.col("interval_id") == b).select("pix"))


def scan_stats(tod: DataFrame) -> DataFrame:
    """Distribution of hits over pixels."""
    return hit_map(tod).agg(F.count("*").alias("n_pix"), F.sum("hits").alias("n_t"), F.min("hits").alias("least"), F.max("hits").alias("most"), F.round(F.avg("hits") + 0.0, 6).alias("mean"), F.round(F.stddev_pop("hits") + 0.0, 6).alias("spread"))


def attack_angles(tod: DataFrame) -> DataFrame:
    """Samples per pixel and polariser angle step."""
    return pointed(tod).groupBy("pix", F.round(F.col("phi") * 4 / F.lit(3.141592653589793)).cast("long").alias("step")).agg(F.count("*").alias("n"))


def coadd(tod: DataFrame, nstokes: int = 1) -> DataFrame:
    """White-noise weighted co-addition: one pass and a closed-form inverse per pixel. Pixels with a singular block give null."""
    if nstokes == 1:
        return pointed(tod).groupBy("pix").agg((F.sum("d") / F.count("*")).alias("i"))
    b = stokes_blocks(tod).join(accumulate(tod, "d", 3), "pix")
    k = inv3_sym("c11", "c12", "c13", "c22", "c23", "c33")
    ok = rcond3_sym("c11", "c12", "c13", "c22", "c23", "c33") > 1e-6
    i, q, u = F.col("i"), F.col("q"), F.col("u")
    x = [k[0] * i + k[1] * q + k[2] * u, k[1] * i + k[3] * q + k[4] * u, k[2] * i + k[4] * q + k[5] * u]
    return b.select("pix", *(F.when(ok, v).alias(n) for n, v in zip("iqu", x)))


def coarse_columns(tod: DataFrame, rank: int | None = None, intervals: int | None = None) -> DataFrame:
    """The a-priori coarse space as (pix, col, z): a pixel's share of hits by interval; or by ``rank`` runs of the ``intervals`` numbered from 0."""
    col = F.col("interval_id") if rank is None else F.floor(F.col("interval_id") * rank / intervals)
    hits = pointed(tod).groupBy("pix", col.cast("long").alias("col")).agg(F.count("*").alias("n"))
    return hits.withColumn("z", F.col("n") / F.sum("n").over(W.partitionBy("pix"))).drop("n")


def comm_bytes(tod: DataFrame, nstokes: int = 1) -> DataFrame:
    """(interval_id, bytes): the partial map that an interval sends in each product."""
    return pointed(tod).select("interval_id", "pix").distinct().groupBy("interval_id").agg((F.count("*") * 8 * nstokes).alias("bytes"))


def operations(tod: DataFrame, lambda_: int | None) -> DataFrame:
    """Operations of a product: samples times (1 + log2 of the band, or of the interval's length)."""
    n = tod.groupBy("interval_id").agg(F.count("*").alias("n"))
    return n.agg(F.sum(F.col("n") * (1 + F.log2(F.lit(lambda_) if lambda_ else F.col("n")))).alias("operations"))
