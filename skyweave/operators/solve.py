"""End-to-end map making, many right-hand sides, the distributed solver, and the measures of runs."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skyweave.functions import inplace
from skyweave.operators import krylov, precond
from skyweave.operators.system import Bands, DistributedOperator, NormalOperator
from skyweave.plans.lineage import cut

#: Bytes of a system matrix of which the driver takes inverses and spectra, which need it several times over.
DENSE = 64 << 20


@dataclass
class Run:
    prec: str
    solution: krylov.Solution
    coarse_dim: int
    build_s: float
    solve_s: float
    op: NormalOperator
    prec_fn: object = None
    coarse: precond.Coarse | None = None
    rank_dropped: int = 0

    def map(self) -> DataFrame:
        return self.op.table(self.solution.x)

    def history(self) -> DataFrame:
        rows = [(self.prec, i, r, s) for i, r, s in self.solution.history]
        return self.op.spark.createDataFrame(rows, "prec string, iter int, rel_residual double, seconds double")


def build(op: NormalOperator, prec: str, rank: int | None = None, eps_tol: float = 0.2, variant: str = "def1", b_prev=None, m_max: int = 200, blocks=None):
    """(preconditioner, Coarse or None). prec: none, bd, ones, apriori, aposteriori, deflation."""
    if prec == "none":
        return precond.identity(), None
    bd = precond.BlockDiagonal(op.diagonal_blocks() if blocks is None else blocks)
    if prec == "bd":
        return bd, None
    if prec == "ones":
        z = precond.ones(len(op.pixels), op.s)
    elif prec in ("apriori", "deflation"):
        k, n = len(op.intervals()), len(op.pixels)
        if rank is not None and rank < k:
            z = precond.a_priori(op.hits_merged(rank), op.s)
        elif k <= n:
            z = precond.a_priori(op.hits()[1], op.s)
        else:  # more columns than pixels: as many as are independent have the same span
            z = precond.a_priori_span(op.hits_gram(), op.hits_merged(1)[:, 0], op.s)
    elif prec == "aposteriori":
        if b_prev is None:
            b_prev = np.random.default_rng(1).standard_normal(op.n)
        z, _ = precond.a_posteriori(op.apply, bd, b_prev, eps_tol, rank, m_max)
        if not z.shape[1]:
            return bd, None
    else:
        raise ValueError(f"unknown preconditioner {prec!r}")
    coarse = precond.Coarse(z, op.image(z, prec in ("apriori", "deflation")))
    if prec == "deflation":
        return precond.identity(), coarse
    return precond.two_level(bd, coarse, variant), coarse


def make_map(tod: DataFrame, model, nstokes: int = 1, prec: str = "bd", tol: float = 1e-6, max_iter: int = 2000, solver: str = "cg", variant: str = "def1", rank: int | None = None, eps_tol: float = 0.2, op: NormalOperator | None = None, b=None, strict: bool = True, length: int = 1 << 20) -> Run:
    op = op or NormalOperator(tod, model, nstokes, length)
    b = op.rhs() if b is None else b
    t = time.perf_counter()
    m, coarse = build(op, prec, rank, eps_tol, variant)
    built = time.perf_counter() - t
    t = time.perf_counter()
    if solver == "gmres":
        s = krylov.gmres(op.apply, m, b, tol)[0]
    elif prec == "deflation":  # CG on the projected system R A x = R b alone; the coarse part is added at the end
        r = precond.deflation(coarse)
        s = krylov.cg(lambda v: r(op.apply(v)), m, r(b), None, tol, max_iter, strict=strict)
        s.x = precond.def2_start(b, coarse, s.x)
    else:
        s = krylov.cg(op.apply, m, b, precond.def2_start(b, coarse) if variant == "def2" and coarse else None, tol, max_iter, strict=strict)
    return Run(prec, s, coarse.z.shape[1] if coarse else 0, built, time.perf_counter() - t, op, m, coarse, coarse.rank_dropped if coarse else 0)


def solve_many(op: NormalOperator, prec_fn, bs: np.ndarray, tol: float = 1e-6, max_iter: int = 500) -> tuple[np.ndarray, np.ndarray]:
    """CG on all columns of bs at once: one pass over the samples per iteration serves every right-hand side still at work."""
    x, r = np.zeros_like(bs), bs.copy()
    z = np.stack([prec_fn(c) for c in r.T], axis=1)
    p, rz, norm = z.copy(), (r * z).sum(axis=0), np.linalg.norm(bs, axis=0)
    took = np.zeros(bs.shape[1], int)
    live = np.flatnonzero(norm > 0)
    for _ in range(max_iter):
        if not len(live):
            break
        q = op.apply_many(p[:, live])
        a = rz[live] / (p[:, live] * q).sum(axis=0)
        x[:, live] += a * p[:, live]
        r[:, live] -= a * q
        took[live] += 1
        live = live[np.linalg.norm(r[:, live], axis=0) > tol * norm[live]]
        if len(live):
            z = np.stack([prec_fn(c) for c in r[:, live].T], axis=1)
            new = (r[:, live] * z).sum(axis=0)
            p[:, live] = z + new / rz[live] * p[:, live]
            rz[live] = new
    return x, took


class Tables:
    """The preconditioner as tables by pixel: inverse Stokes blocks, and for the two-level form the rows of Z and A Z with E^-1 on the driver.

    Z and A Z are never on the driver; of size rank are only Z'r and the coarse solution, and of its square E. ``rank`` is therefore bounded."""

    MOST = 4096

    def __init__(self, op: DistributedOperator, rank: int = 0):
        if rank > self.MOST:
            raise ValueError(f"a coarse space of {rank} columns; at most {self.MOST} have E on the driver")
        self.op, self.s, self.r, self.rank_dropped = op, op.s, rank, 0
        self.inverse = None
        blocks = self._blocks()
        if not rank:
            self.rows = cut(blocks)
            return
        z = cut(op.a_priori(rank))
        az = cut(op.apply_coarse(z))
        cells = z.select("pix", F.col("col").alias("i"), "z").join(az.select("pix", F.col("col").alias("j"), F.col("v0").alias("a")), "pix")
        e = np.zeros((rank, rank))
        for c in cells.groupBy("i", "j").agg(F.sum(F.col("z") * F.col("a")).alias("v")).collect():  # rank * rank cells
            e[c["i"], c["j"]] = c["v"]
        d, v = np.linalg.eigh((e + e.T) / 2)
        keep = d > 1e-12 * d.max()
        self.rank_dropped, self.inverse, self.e = int((~keep).sum()), (v[:, keep] / d[keep]) @ v[:, keep].T, e
        zs = z.groupBy("pix").agg(F.sort_array(F.collect_list(F.struct("col", "z"))).alias("z")).select("pix", F.col("z.col").alias("zc"), F.col("z.z").alias("zv"))
        azs = az.groupBy("pix").agg(F.sort_array(F.collect_list(F.struct("col", *op.names))).alias("a")).select("pix", F.col("a.col").alias("ac"), *(F.col(f"a.{n}").alias(f"a{i}") for i, n in enumerate(op.names)))
        self.rows = cut(blocks.join(zs, "pix").join(azs, "pix"))

    def _blocks(self) -> DataFrame:
        """(pix, b): the inverse of each pixel's block of P' diag(W) P, row by row."""
        op, s = self.op, self.s
        if s == 1:
            w0 = F.create_map(*(F.lit(x) for k in op.model.kernels for x in (k, op.model.diag(k))))
            from skyweave.operators.system import core_pixels

            hits = op.blocks.select(w0[F.col("noise_id")].alias("w"), F.explode(core_pixels()).alias("pix"))
            return hits.groupBy("pix").agg(F.array(1 / F.sum("w")).alias("b"))
        cells = op.diagonal_cells()

        def run(batches):
            for b in batches:
                m = np.stack([b.column(1 + k).to_numpy() for k in range(s * s)], axis=1).reshape(-1, s, s)
                inv = precond.BlockDiagonal(m).inverse.reshape(len(m), s * s) if len(m) else m.reshape(0, s * s)
                yield pa.record_batch([b.column(0), pa.array(list(inv), pa.list_(pa.float64()))], names=["pix", "b"])

        return cells.mapInArrow(run, "pix long, b array<double>")

    def apply(self, r: DataFrame, names: list[str]) -> DataFrame:
        """The columns of r (pix, ``names``.., others) with m0.. = M r added."""
        s, inverse = self.s, self.inverse
        met = r.join(self.rows, "pix")
        if inverse is not None:
            dots = met.select(F.explode(F.arrays_zip("zc", "zv")).alias("x"), names[0]).groupBy("x.zc").agg(F.sum(F.col("x.zv") * F.col(names[0])).alias("v")).collect()  # rank numbers
            zr = np.zeros(self.r)
            for c in dots:
                zr[c["zc"]] = c["v"]
            c = inverse @ zr
            coefficients = F.array(*map(F.lit, c.tolist()))
            take = lambda cols, vals: F.aggregate(F.zip_with(cols, vals, lambda i, v: v * F.element_at(coefficients, i + 1)), F.lit(0.0), lambda t, x: t + x)
            met = met.withColumns({f"_u{i}": F.col(names[i]) - take(F.col("ac"), F.col(f"a{i}")) for i in range(s)} | {"_zc": take(F.col("zc"), F.col("zv"))})
        else:
            met = met.withColumns({f"_u{i}": F.col(names[i]) for i in range(s)} | {"_zc": F.lit(0.0)})
        out = {f"m{i}": sum((F.col("b")[i * s + j] * F.col(f"_u{j}") for j in range(s)), F.col("_zc") if i == 0 else F.lit(0.0)) for i in range(s)}
        return met.select(*r.columns, *(v.alias(k) for k, v in out.items()))


def distributed_cg(op: DistributedOperator, tol: float = 1e-8, max_iter: int = 200, rank: int = 0) -> tuple[DataFrame, list[float]]:
    """CG where every vector is a table by pixel, with the standard preconditioner, or with ``rank`` a-priori columns the two-level one (def1); lineage is cut each iteration.
    The step uses the difference of residuals, as that preconditioner is not symmetric."""
    s, m = op.s, Tables(op, rank)
    ix, ir, ip, iq = ([f"{c}{i}" for i in range(s)] for c in "xrpq")
    im = [f"m{i}" for i in range(s)]
    dot = lambda a, b: F.sum(sum((F.col(x) * F.col(y) for x, y in zip(a, b)), F.lit(0.0)))
    b = op.rhs().select("pix", *(F.col(f"v{i}").alias(f"r{i}") for i in range(s)))
    state = cut(m.apply(cut(b.withColumns({x: F.lit(0.0) for x in ix})), ir).withColumns({p: F.col(z) for p, z in zip(ip, im)}))
    first = state.agg(dot(ir, ir).alias("rr"), dot(ir, im).alias("rz")).first()
    norm, rz, history = math.sqrt(first["rr"] or 0.0), first["rz"], [1.0]
    while norm > 0 and history[-1] > tol and len(history) <= max_iter:
        q = op.apply(state.select("pix", *(F.col(p).alias(f"v{i}") for i, p in enumerate(ip)))).select("pix", *(F.col(f"v{i}").alias(x) for i, x in enumerate(iq)))
        met = cut(state.select("pix", *ix, *ir, *ip, *im).join(q, "pix"))
        pq = met.agg(dot(ip, iq)).first()[0]
        if pq <= 0 or rz <= 0:
            raise krylov.NonConvergence(f"iteration {len(history)}: p'Ap = {pq:.3g}, r'z = {rz:.3g}", history)
        alpha = rz / pq
        moved = met.select("pix", *((F.col(x) + alpha * F.col(p)).alias(x) for x, p in zip(ix, ip)), *((F.col(r) - alpha * F.col(v)).alias(r) for r, v in zip(ir, iq)), *ip, *(F.col(r).alias(f"o{i}") for i, r in enumerate(ir)))
        new = cut(m.apply(cut(moved) if rank else moved, ir))
        got = new.agg(dot(ir, ir).alias("rr"), dot(ir, im).alias("rz"), dot([f"o{i}" for i in range(s)], im).alias("oz")).first()
        history.append(math.sqrt(got["rr"]) / norm)
        step = (got["rz"] - got["oz"]) / rz
        state = new.select("pix", *ix, *ir, *im, *((F.col(z) + step * F.col(p)).alias(p) for z, p in zip(im, ip)))
        rz = got["rz"]
    return state.select("pix", *(F.col(x).alias(n) for x, n in zip(ix, "iqu"))), history


def solve_map(tod: DataFrame, model, nstokes: int = 1, prec: str = "bd", rank: int | None = None, tol: float = 1e-6, budget: int | None = None, length: int = 1 << 20) -> DataFrame:
    """The map by vectors on the driver where they and the coarse space fit ``budget`` bytes, and by tables beyond (bd or apriori)."""
    from skyweave.operators.pointing import pointed
    from skyweave.plans import strategy

    n = pointed(tod).select("pix").distinct().count()
    k = tod.select("interval_id").distinct().count() if prec == "apriori" else 0
    r = min(k, rank or k)
    plan = strategy.choose(n, nstokes, 2 * r, budget or strategy.BROADCAST_BUDGET)
    if plan.kind == "broadcast":
        return make_map(tod, model, nstokes, prec, tol, rank=rank, length=length).map()
    if prec not in ("bd", "apriori"):
        raise ValueError(f"{prec!r} needs vectors on the driver; {plan.explain()}")
    return distributed_cg(DistributedOperator(tod, model, nstokes, length), tol, 2000, min(r, Tables.MOST))[0]


def scaling(spark, tod, model, circles: list[int], tasks: list[int], prec: str = "bd", nstokes: int = 1, tol: float = 1e-6, **how) -> list[tuple]:
    """(circles, tasks, samples, iterations, build seconds, solve seconds, seconds an iteration) of solves of ``tod(n)``, n circles dealt to so many tasks:
    weak scaling where both grow together, strong where the circles stay."""
    return [r[1:] for r in scalings(spark, tod, model, circles, tasks, {prec: how}, nstokes, tol)]


def scalings(spark, tod, model, circles: list[int], tasks: list[int], precs: dict[str, dict], nstokes: int = 1, tol: float = 1e-6) -> list[tuple]:
    """The rows of ``scaling``, each after its preconditioner. So many circles are packed once and only dealt anew for other tasks and solves."""
    out, op, samples = [], None, {}
    for k, (n, t) in enumerate(zip(circles, tasks)):
        if op is None or n != circles[k - 1]:
            if op is not None:
                op.close()
            op = NormalOperator(tod(n), model, nstokes)
            samples[n] = int(op.blocks.agg(F.sum(F.col("core_hi") - F.col("core_lo"))).first()[0])
        dealt = op.dealt(t)
        b = dealt.rhs()  # deals the blocks, too
        for prec, how in precs.items():
            run = make_map(None, None, nstokes, prec, tol, op=dealt, b=b, strict=False, **how)
            out.append((prec, n, t, samples[n], run.solution.iterations, run.build_s, run.solve_s, run.solve_s / max(1, run.solution.iterations)))
        dealt.close()
    if op is not None:
        op.close()
    return [r for prec in precs for r in out if r[0] == prec]


# ---- measures ----

def iterations_to(history, tol: float) -> int | None:
    return next((i for i, r, _ in history if r <= tol), None)


def iteration_gain(standard: Run, other: Run) -> float:
    return standard.solution.iterations / max(1, other.solution.iterations)


def speedups(standard: Run, other: Run, n_rhs: int = 1) -> dict[str, float]:
    """Quotients to the standard run: solving alone, with construction, and with construction spread over n right-hand sides."""
    return {
        "speedup_solve": standard.solve_s / other.solve_s,
        "speedup_total": (standard.build_s + standard.solve_s) / (other.build_s + other.solve_s),
        "speedup_amortised": (standard.build_s / n_rhs + standard.solve_s) / (other.build_s / n_rhs + other.solve_s),
        "speedup_iterations": iteration_gain(standard, other),
    }


def breakdown(op: NormalOperator, coarse: precond.Coarse | None, bd, n: int = 3) -> dict[str, float]:
    """Seconds per application of the steps of an iteration: the whole product, of it noise weighting (timed in its tasks, summed over them and spread over the cores) and what is
    left for expanding, accumulating and reducing; the standard preconditioner, E's solve and the products with Z and A Z."""
    r = np.random.default_rng(0).standard_normal(op.n)
    out = {}
    steps = {"product": lambda: op.apply(r), "standard": lambda: bd(r)}
    if coarse:
        steps |= {"coarse_solve": lambda: coarse.inverse @ r[: coarse.inverse.shape[0]], "coarse_products": lambda: coarse.az @ (coarse.z.T @ r)}
    for name, f in steps.items():
        t = time.perf_counter()
        for _ in range(n):
            f()
        out[name] = (time.perf_counter() - t) / n
    cores = min(op.tasks, op.spark.sparkContext.defaultParallelism)
    out["noise_weighting"] = min(out["product"], op.weighting_seconds() / cores)
    out["accumulate_reduce"] = out["product"] - out["noise_weighting"]
    return out


def variance_by_pixel(maps: np.ndarray) -> np.ndarray:
    """Variance over realisations (columns) of each pixel."""
    return maps.var(axis=1)


def dense(op: NormalOperator) -> np.ndarray | Bands:
    """The system matrix: formed in one pass where it and what is made of it fit the driver, or in bands that tasks keep."""
    if op.form(DENSE).a is not None:
        return op.a
    return op.banded()


def spectrum(a: np.ndarray | Bands, prec_fn=None) -> np.ndarray:
    """Eigenvalues of M A in ascending order of their real parts."""
    if isinstance(a, Bands):
        return spectra(a, [prec_fn])[0]
    if prec_fn is None:
        return np.linalg.eigvalsh(a)
    if isinstance(prec_fn, precond.BlockDiagonal):  # symmetric: those of L' A L for M = L L'
        n, k, _ = prec_fn.inverse.shape
        low = np.linalg.cholesky(prec_fn.inverse)
        left = np.einsum("pji,pjc->pic", low, a.reshape(n, k, -1)).reshape(a.shape)
        both = np.einsum("pji,pjc->pic", low, np.ascontiguousarray(left.T).reshape(n, k, -1)).reshape(a.shape)
        return np.linalg.eigvalsh((both + both.T) / 2)
    return np.sort(np.linalg.eigvals(prec_fn(a)).real)


def spectra(a: np.ndarray | Bands, prec_fns: list) -> list[np.ndarray]:
    """The spectrum of M A for each M of a list; those of a matrix in bands are made side by side, each by a task that holds the matrix once."""
    if not isinstance(a, Bands):
        return [spectrum(a, f) for f in prec_fns]
    found = a.whole([_symmetric(f) for f in prec_fns])
    return [np.sort(np.concatenate((_coarse_values(a, f), v[f.coarse.kept.shape[1] :]))) if isinstance(f, precond.TwoLevel) else v for f, v in zip(prec_fns, found)]


def _symmetric(prec_fn):
    """The work of a task that has A: the eigenvalues of a symmetric matrix, made in A's memory. None: A. BD = L L': L' A L. Two levels: L' R A L, which for def2 is
    L' R A R' L; its zeros, one for each coarse column that was kept, come first and stand for the coarse values."""
    if prec_fn is None:
        return inplace.eigenvalues
    two = isinstance(prec_fn, precond.TwoLevel)
    bd = prec_fn.bd if two else prec_fn
    if not isinstance(bd, precond.BlockDiagonal):
        raise ValueError("a matrix in bands has spectra of itself, and with the standard and the two-level preconditioners")
    low = np.linalg.cholesky(bd.inverse)
    less = None
    if two:
        c = prec_fn.coarse
        left = c.az @ c.inverse
        if prec_fn.variant == "def2":
            left = left + (c.az - left @ (c.z.T @ c.az)) @ c.inverse
        less = left, c.az

    def work(a):
        n, k, _ = low.shape
        step = max(1, (16 << 20) // (8 * a.shape[1] * k))
        for lo in range(0, n, step):
            some = slice(lo * k, min(lo + step, n) * k)
            rows = a[some]
            if less is not None:
                rows -= less[0][some] @ less[1].T
            rows = np.einsum("pji,pjc->pic", low[lo : lo + step], rows.reshape(-1, k, a.shape[1]))
            a[some] = np.einsum("rpj,pji->rpi", rows.reshape(-1, n, k), low).reshape(-1, n * k)
        return inplace.eigenvalues(a)

    return work


def _coarse_values(a: Bands, f: precond.TwoLevel) -> np.ndarray:
    """Eigenvalues of M A that belong to the coarse space, by applying M. For def1 M A maps the space Q to itself: those of Q' M A Q. For def2 it maps what is A-orthogonal to Q to
    itself, and acts on the rest as (Q' A M A Q) (Q' A Q)^-1. Both are checked, as the other values are complete for that alone."""
    c = f.coarse
    q, r = np.linalg.qr(c.z @ c.kept)
    aq = np.linalg.solve(r.T, (c.az @ c.kept).T).T
    moved = f(aq)
    if f.variant == "def1":
        t = q.T @ moved
        off = np.abs(moved - q @ t).max()
    else:
        t = np.linalg.solve((q.T @ aq).T, (aq.T @ moved).T).T
        x = np.random.default_rng(0).standard_normal((len(q), 4))
        x -= q @ np.linalg.solve(q.T @ aq, aq.T @ x)
        off = np.abs(aq.T @ f(a @ x)).max() / np.abs(aq).max()
    if off > 1e-6:
        raise ArithmeticError(f"the coarse space is not kept by {f.variant}: {off:.3g}")
    return np.linalg.eigvals(t).real


def condition_number(values: np.ndarray, floor: float = 1e-12) -> float:
    v = values[values > floor * values.max()]
    return float(v.max() / v.min())


def a_norm_error(a: np.ndarray, x: np.ndarray, ref: np.ndarray) -> float:
    d = x - ref
    return float(math.sqrt(max(0.0, d @ a @ d)))


def plateau(history, low: float = 3e-5, high: float = 3e-3) -> int:
    """Iterations spent with a residual in a band."""
    return sum(low <= r <= high for _, r, _ in history)


def cost_model(lengths: list[int], lambda_: int | None, iterations: int) -> float:
    """Operations: iterations * sum over intervals of length * (1 + log2 of the band, or of the length)."""
    return iterations * sum(n * (1 + math.log2(max(2, lambda_ if lambda_ else n))) for n in lengths)


def map_rms(x: np.ndarray, ref: np.ndarray, offset: bool = True) -> float:
    d = x - ref
    return float(np.std(d) if offset else np.sqrt(np.mean(d * d)))


def bias(x: np.ndarray, ref: np.ndarray) -> float:
    return float(np.mean(x - ref))


def solved(a: np.ndarray | Bands, b: np.ndarray) -> np.ndarray:
    """Dense inversion. A matrix in bands is solved by a task that holds it once."""
    if isinstance(a, Bands):
        return a.whole([lambda m: inplace.solve(m, b)])[0]
    return np.linalg.solve(a, b)


def direct(op: NormalOperator, b: np.ndarray | None = None) -> np.ndarray:
    """Dense inversion (cubic in pixels): the baseline for small maps."""
    return solved(dense(op), op.rhs() if b is None else b)
