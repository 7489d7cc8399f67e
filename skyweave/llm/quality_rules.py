"""Quality rules with robust multivariate outliers.

Statistics of every whole text, then a minimum-covariance-determinant estimate for every (lang, source) group: from three starts
(coordinate-wise medians and absolute deviations; the covariances of the spatial signs and of bounded scores about them), concentration steps
take the moments of the ``share`` of rows nearest to the present centre; the start whose determinant is smallest after ``first`` steps goes on for ``more``, and a
last step takes all rows within the 97.5 % quantile. The subset is exact: its largest distance is found in two counts over the group's
distances, in steps of 2**-22 of an octave, and ties at it belong to it. All is Spark aggregates over all rows, for all groups and for all documents
together at once; a hot group is pre-aggregated in its tasks. A group's moments are drawn towards those of all documents by the weight of ``prior`` rows, at
any size of the group. A text is rejected if a base rule fails or if the Mahalanobis distance of its transformed statistics, squared, exceeds ``cutoff``.

Edge cases: null and empty texts have zero words, so base_failed; null lang or source form groups of their own; repeated rows
count as often as they occur; constant statistics are held by a floor on the variances; rows of a group without any row that
passes the base rules have no distance; extra columns are ignored."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import common as C

_SYMBOLS = b"#*$%&|<>"
_DELETE_REST = bytes(b for b in range(256) if b not in _SYMBOLS)
DIMS = 4
#: Spread that the transformed statistics of clean texts may have by themselves, added to every estimate.
FLOOR = (0.12, 0.4, 0.8, 1.0)


def statistics(text: bytes | None) -> tuple[int, int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, lines with a word."""
    t = text or b""
    words = t.split()
    n = len(words)
    if not n:
        return 0, 0, 0, 0, 0, 0
    joined = np.frombuffer(b"".join(words), np.uint8)
    chars = int(((joined & 0xC0) != 0x80).sum())
    symbols = len(t.translate(None, _DELETE_REST))
    lines = [x for x in t.split(b"\n") if x and x.split(None, 1)]
    repeat = 0
    if n >= 5:
        g = C.rolling(C.hashed(words), 5)
        s = np.sort(g)
        twice = np.unique(s[1:][s[1:] == s[:-1]])
        if len(twice):
            hit = np.isin(g, twice).astype(np.int8)
            d = np.zeros(n + 1, np.int64)
            d[:-5] += hit
            d[5:] -= hit
            repeat = int((np.cumsum(d)[:-1] > 0).sum())
    return n, chars, symbols, len(lines) - len(set(lines)), repeat, len(lines)


def _measure(batches):
    for batch in batches:
        rows = [statistics(t) for t in C.texts(batch)]
        c = np.array(rows, np.int64).reshape(-1, 6)
        yield pa.record_batch([batch.column(0), batch.column(1), batch.column(2), *(pa.array(c[:, i]) for i in range(6))], names=["doc_id", "lang", "source", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines"])


def measured(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source, the statistics, base_failed and the transformed vector x0..x3."""
    src = docs.select("doc_id", F.coalesce(F.col("lang").cast("string"), F.lit("\0")).alias("lang"), F.coalesce(F.col("source").cast("string"), F.lit("\0")).alias("source"), F.col("text").cast("string").alias("text"))
    m = src.mapInArrow(C.task(_measure), f"doc_id {src.schema['doc_id'].dataType.simpleString()}, lang string, source string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_lines long")
    n = F.greatest("n_words", F.lit(1))
    return m.withColumns({
        "base_failed": (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words")),
        "x0": F.log(F.greatest(F.col("word_chars") / n, F.lit(0.1))),
        "x1": F.log1p(100.0 * F.col("n_symbols") / n),
        "x2": F.log1p(100.0 * F.col("n_dup_lines") / F.greatest("n_lines", F.lit(1))),
        "x3": F.log1p(100.0 * F.col("n_repeat_words") / n),
    })


#: Groups (of some 200 bytes each) whose estimates may be broadcast; beyond that they are shuffled to the same join.
MOST_GROUPS = 50_000
KEYS = ["lang", "source", "common"]
_CELLS = [(i, j) for i in range(DIMS) for j in range(i, DIMS)]
_MOMENTS = [f"m{i}" for i in range(DIMS)] + [f"c{i}{j}" for i, j in _CELLS]
_ESTIMATE = ["n", "det", *(f"m{i}" for i in range(DIMS)), *(f"p{i}{j}" for i, j in _CELLS)]


def chi2(x: float, k: int) -> float:
    """Distribution function of the squared length of k (an even number) normal dimensions."""
    term = total = math.exp(-x / 2)
    for j in range(1, k // 2):
        term *= x / 2 / j
        total += term
    return 1 - total


def chi2_quantile(p: float, k: int) -> float:
    lo, hi = 0.0, 1000.0
    for _ in range(100):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if chi2(mid, k) < p else (lo, mid)
    return lo


def consistency(share: float) -> float:
    """What the covariance of the nearest ``share`` of normal rows is multiplied by to be that of all."""
    return share / chi2(chi2_quantile(share, DIMS), DIMS + 2)


def _moments(names: list[str], prefix: str = "") -> list[Column]:
    x = [F.col(n) for n in names]
    return [*(F.avg(x[i]).alias(f"{prefix}m{i}") for i in range(DIMS)), *(F.covar_pop(x[i], x[j]).alias(f"{prefix}c{i}{j}") for i, j in _CELLS)]


def covariance(col: dict, prefix: str = "c") -> np.ndarray:
    """Matrices of the cells of many groups."""
    n = len(next(iter(col.values())))
    s = np.empty((n, DIMS, DIMS))
    for i, j in _CELLS:
        s[:, i, j] = s[:, j, i] = col[f"{prefix}{i}{j}"]
    return s


def _table(keys: dict, start: np.ndarray | None, n: np.ndarray, m: np.ndarray, s: np.ndarray) -> pa.RecordBatch:
    """Estimates as a batch: centre, inverse of the covariance with the floors added, and its determinant."""
    s = s + np.diag(np.square(FLOOR))
    inv = np.linalg.inv(s) if len(s) else s
    out = {**keys, **({} if start is None else {"start": pa.array(start.astype(np.int32))}), "n": pa.array(n.astype(np.int64)), "det": pa.array(np.linalg.det(s) if len(s) else np.zeros(0))}
    out |= {f"m{i}": pa.array(m[:, i].copy()) for i in range(DIMS)} | {f"p{i}{j}": pa.array(inv[:, i, j].copy()) for i, j in _CELLS}
    return pa.record_batch(list(out.values()), names=list(out))


def _schema(start: bool) -> str:
    return ", ".join(["lang string, source string, common int", *(["start int"] if start else []), "n long", *(f"{c} double" for c in _ESTIMATE[1:])])


def _columns(b: pa.RecordBatch) -> tuple[dict, dict]:
    """Key columns as they are, the others as arrays of numbers."""
    at = {name: b.column(i) for i, name in enumerate(b.schema.names)}
    return {k: at[k] for k in KEYS}, {c: np.nan_to_num(v.to_numpy(zero_copy_only=False).astype(float)) for c, v in at.items() if c not in KEYS}


def _estimates(scale: float):
    """Moments of each group and start -> estimates."""

    def run(batches):
        for b in batches:
            keys, col = _columns(b)
            yield _table(keys, col["start"], col["n"], np.stack([col[f"m{i}"] for i in range(DIMS)], 1), covariance(col) * scale)

    return run


def _starts(batches):
    """The three starts of each group, from its medians, scales, and the covariances of signs and scores."""
    for b in batches:
        keys, col = _columns(b)
        m, s = (np.stack([col[f"{x}{i}"] for i in range(DIMS)], 1) for x in "ms")
        both = s[:, :, None] * s[:, None, :]
        for k, cov in enumerate((np.eye(DIMS) * both, covariance(col, "sign_c") * DIMS * both, covariance(col, "score_c") * both)):
            yield _table(keys, np.full(b.num_rows, k), col["n"], m, cov)


def distance() -> Column:
    """Squared Mahalanobis distance of x0..x3 from m0.. under p00.."""
    d = [F.col(f"x{i}") - F.col(f"m{i}") for i in range(DIMS)]
    out = F.lit(0.0)
    for i, j in _CELLS:
        out = out + (1.0 if i == j else 2.0) * d[i] * d[j] * F.col(f"p{i}{j}")
    return out


def _meet(rows: DataFrame, groups: DataFrame, keys: list[str], small: bool) -> DataFrame:
    """Rows with their group's values: broadcast while the groups were counted to be few, so a hot group stays spread; else a join."""
    return rows.join(F.broadcast(groups) if small else groups, keys)


def nearest(near: DataFrame, keys: list[str], share: float, small: bool) -> DataFrame:
    """The rows whose distance d2 is at most that of the group's ceil(share * n)-th: ``at``, the distance in steps of 2**-22 of an octave,
    is counted by its upper digits, then by all digits within the one step that holds it."""
    near = near.withColumn("at", F.floor(F.log2(F.greatest("d2", F.lit(0.0)) + 2.0**-30) * (1 << 22)).cast("long"))
    upto = W.partitionBy(*keys).orderBy("k").rowsBetween(W.unboundedPreceding, W.currentRow)  # at most 2**16 or so counts a group
    first = lambda c: c.withColumn("upto", F.sum("rows").over(upto)).where("upto >= need").groupBy(*keys).agg(F.min_by(F.struct("k", "rows", "upto", "need"), "k").alias("x"))
    need = F.ceil(F.lit(share) * F.col("n")).alias("need")
    coarse = first(near.groupBy(*keys, F.shiftright("at", 16).alias("k"), need).agg(F.count("*").alias("rows")))
    step = coarse.select(*keys, F.col("x.k").alias("step"), (F.col("x.need") - F.col("x.upto") + F.col("x.rows")).alias("need"))
    within = _meet(near.select(*keys, "at"), step, keys, small).where(F.shiftright("at", 16) == F.col("step"))
    most = first(within.groupBy(*keys, F.col("at").alias("k"), "need").agg(F.count("*").alias("rows"))).select(*keys, F.col("x.k").alias("most"))
    return _meet(near, most, keys, small).where("at <= most")


def robust(good: DataFrame, share: float = 0.75, first: int = 2, more: int = 2) -> DataFrame:
    """Per group of ``good`` (lang, source, common, x0..): n, det, centre and inverse covariance, and the moments of the last step."""
    middle = good.groupBy(*KEYS).agg(F.count("*").alias("n"), *(F.percentile_approx(f"x{i}", 0.5, 1000).alias(f"m{i}") for i in range(DIMS)))
    middle = C.cut(middle)
    small = middle.limit(MOST_GROUPS + 1).count() <= MOST_GROUPS
    off = _meet(good, middle, KEYS, small).groupBy(*KEYS).agg(*(F.percentile_approx(F.abs(F.col(f"x{i}") - F.col(f"m{i}")), 0.5, 1000).alias(f"s{i}") for i in range(DIMS)))
    scaled = C.cut(middle.join(off, KEYS).withColumns({f"s{i}": F.greatest(1.4826 * F.col(f"s{i}"), F.lit(FLOOR[i])) for i in range(DIMS)}))
    z = _meet(good, scaled, KEYS, small).withColumns({f"z{i}": (F.col(f"x{i}") - F.col(f"m{i}")) / F.col(f"s{i}") for i in range(DIMS)})
    size = F.sqrt(sum((F.col(f"z{i}") * F.col(f"z{i}") for i in range(DIMS)), F.lit(1e-18)))
    z = z.withColumns({f"u{i}": F.col(f"z{i}") / size for i in range(DIMS)} | {f"t{i}": F.tanh(f"z{i}") for i in range(DIMS)})
    both = z.groupBy(*KEYS).agg(*(F.avg(F.col(f"u{i}") * F.col(f"u{j}")).alias(f"sign_c{i}{j}") for i, j in _CELLS), *(F.covar_pop(f"t{i}", f"t{j}").alias(f"score_c{i}{j}") for i, j in _CELLS))
    now = C.cut(scaled.join(both, KEYS).mapInArrow(_starts, _schema(True)))
    keys = [*KEYS, "start"]
    for k in range(first + more):
        near = _meet(good, now, KEYS, small).withColumn("d2", distance()).select(*keys, "n", "d2", *(f"x{i}" for i in range(DIMS)))
        made = nearest(near, keys, share, small).groupBy(*keys).agg(F.first("n").alias("n"), *_moments([f"x{i}" for i in range(DIMS)])).mapInArrow(_estimates(consistency(share)), _schema(True))
        if k == first - 1:  # the start with the smallest determinant, the first of equals
            made = made.groupBy(*KEYS).agg(F.min_by(F.struct("start", *_ESTIMATE), F.struct("det", "start")).alias("x")).select(*KEYS, "x.*")
        now = C.cut(made)
    near = _meet(good, now, KEYS, small).withColumn("d2", distance()).where(F.col("d2") <= chi2_quantile(0.975, DIMS))
    return C.cut(near.groupBy(*KEYS).agg(F.first("n").alias("n"), *_moments([f"x{i}" for i in range(DIMS)])))


def drawn(prior: float, centre: np.ndarray, spread: np.ndarray):
    """Moments -> estimates, drawn towards ``centre`` and ``spread`` as by ``prior`` rows with these."""
    scale = consistency(0.975)

    def run(batches):
        for b in batches:
            keys, col = _columns(b)
            m = np.stack([col[f"m{i}"] for i in range(DIMS)], 1)
            w = col["n"] / (col["n"] + prior)
            d = m - centre
            s = w[:, None, None] * covariance(col) * scale + (1 - w)[:, None, None] * spread + (w * (1 - w))[:, None, None] * d[:, :, None] * d[:, None, :]
            yield _table(keys, None, col["n"], centre + w[:, None] * d, s)

    return run


def judge(docs: DataFrame, cutoff: float = 30.0, prior: float = 20.0) -> DataFrame:
    """Statistics, base_failed, distance and kept of every row."""
    rows = C.cut(measured(docs))
    # the base rules' failures take no part in the estimates: every row that passes them does, in its group and among all
    good = rows.where("not base_failed").select("lang", "source", *(f"x{i}" for i in range(DIMS)), F.explode(F.array(F.lit(0), F.lit(1))).alias("common"))
    good = good.withColumns({k: F.when(F.col("common") == 0, F.col(k)).otherwise(F.lit("")) for k in ("lang", "source")})
    found = robust(good)
    all_ = found.where("common = 1").collect()  # one row
    if all_:
        col = {c: np.array([all_[0][c]], float) for c in _MOMENTS}
        centre, spread = np.array([col[f"m{i}"][0] for i in range(DIMS)]), covariance(col)[0] * consistency(0.975)
    else:
        centre, spread = np.zeros(DIMS), np.eye(DIMS)
    own = C.cut(found.where("common = 0").mapInArrow(drawn(prior, centre, spread), _schema(False))).drop("common")
    small = own.limit(MOST_GROUPS + 1).count() <= MOST_GROUPS
    out = rows.join(F.broadcast(own) if small else own, ["lang", "source"], "left").withColumn("distance", distance())
    kept = ~F.col("base_failed") & F.coalesce(F.col("distance") <= cutoff, F.lit(True))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "distance", kept.alias("kept"))


def op4_quality_rules(spark, sf_dir: str) -> DataFrame:
    return judge(C.table(spark, sf_dir, "documents")).drop("distance")
