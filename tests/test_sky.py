import math

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from skyweave.functions import kernels as K
from skyweave.operators import arrange, krylov, precond
from skyweave.operators import pointing as P
from skyweave.operators import solve as S
from skyweave.operators import system
from skyweave.operators.system import DistributedOperator, NormalOperator
from skyweave.plans import strategy
from skyweave.sources import workloads as WL

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def dense_weights(w, n):
    out = np.zeros((n, n))
    for i in range(n):
        for j in range(n):
            if abs(i - j) < len(w):
                out[i, j] = w[abs(i - j)]
    return out


@pytest.mark.parametrize("n", [1, 2, 7, 64, 333])
def test_weight_equals_dense_block(n):
    w = K.kernel(0.1, 32)
    y = np.random.default_rng(n).standard_normal((3, n))
    assert np.allclose(K.weight(y, w), y @ dense_weights(w, n), atol=1e-12)


def test_growing_window_is_rejected():
    w = K.kernel(0.02, 100, kind="cut") * np.exp(2 * (np.arange(101) / 100) ** 2)
    with pytest.raises(ValueError):
        K.check_positive(w)
    K.check_positive(K.kernel(0.02, 100))


@pytest.mark.parametrize("f_cut", [0.01, 0.05])
def test_weights_without_low_modes_are_positive(f_cut):
    from skyweave import registry

    n = 4000
    for noise_id, w in registry.cut_model(f_cut).kernels.items():
        slow = np.stack([np.cos(math.pi * m * (np.arange(n) + 0.5) / n) for m in range(1, 400)])
        assert ((K.weight(slow, w) * slow).sum(axis=1) > 0).all()
        with pytest.raises(ValueError):
            K.check_positive(K.kernel(registry.KNEES[noise_id], 128, f_cut=f_cut))


def test_band_rules():
    assert K.min_lossless_lambda(1 / (100 * math.pi)) == 100
    assert K.white_equivalent_lambda(1 / (100 * math.pi)) == 100
    assert math.isclose(K.deflection_frequency(100), 1 / (100 * math.pi))
    assert K.fast_length(1009) == 1024 and K.fast_length(961) == 972


def test_strategy():
    assert strategy.choose(1000, 3).kind == "broadcast"
    assert strategy.choose(10**9, 3).kind == "shuffle"
    assert strategy.halo_overhead(1 << 20, 1 << 13) < 0.02


@pytest.fixture(scope="module")
def w0(spark):
    model = K.Stationary({0: K.kernel(0.05, 16), 1: K.kernel(0.1, 16)})
    tod = WL.tod_w0(spark, SF).cache()
    return tod, model, NormalOperator(tod, model)


def test_halo_split_and_distributed_agree(w0):
    tod, model, op = w0
    x = np.arange(op.n, dtype=float)
    split = NormalOperator(tod, model, length=10)
    assert np.allclose(op.apply(x), split.apply(x))
    d = DistributedOperator(tod, model, length=10)
    xs = op.table(x).withColumnRenamed("i", "v0")
    got = {r.pix: r.v0 for r in d.apply(xs).collect()}
    assert np.allclose(op.apply(x), [got[p] for p in op.pixels.tolist()])


def test_algebra(w0):
    _, _, op = w0
    a = S.dense(op)
    assert np.allclose(a, a.T) and np.linalg.eigvalsh(a)[0] > 0
    bd = precond.BlockDiagonal(op.diagonal_blocks())
    z = precond.merge_columns(precond.a_priori(op.hits()[1]), 4)
    assert np.allclose(z.sum(axis=1), 1)
    c = precond.Coarse(z, op.apply_many(z, sparse=True))
    assert np.allclose(c.az, a @ z)
    r = precond.deflation(c)
    assert np.allclose(r(c.az), 0, atol=1e-9)
    v = np.random.default_rng(0).standard_normal(op.n)
    assert np.allclose(r(r(v)), r(v)) and np.allclose(z.T @ r(v), 0, atol=1e-9)
    two = precond.two_level(bd, c)
    assert np.allclose(np.stack([two(q) for q in c.az.T], axis=1), z)
    s1, s2 = (S.spectrum(a, precond.two_level(bd, c, k)) for k in ("def1", "def2"))
    assert np.allclose(s1, s2, atol=1e-8)
    doubled = np.concatenate((z, z[:, :1]), axis=1)
    assert precond.Coarse(doubled, a @ doubled).rank_dropped == 1


@pytest.mark.parametrize("nstokes, length", [(1, 1 << 20), (1, 10), (3, 10)])
def test_formed_matrix_equals_products(spark, w0, nstokes, length):
    """One pass gives the matrix of the products, with halos, cut slots and polarised samples."""
    _, model, _ = w0
    tod = WL.tod_w0(spark, SF, nstokes == 3)
    tod = P.pixel_cut(tod)[0] if nstokes == 3 else tod
    op = NormalOperator(tod, model, nstokes, length)
    x = np.random.default_rng(0).standard_normal((op.n, 3))
    want = op.apply_many(x)
    assert op.form(1).a is None and np.allclose(op.form().apply_many(x), want, atol=1e-9) and np.allclose(op.a, op.a.T)
    assert op.tasks <= spark.sparkContext.defaultParallelism


@pytest.mark.parametrize("k", [1, 3])
def test_spectrum_of_a_block_preconditioner(k, monkeypatch):
    """Real by a symmetric form, equal to that of the product; other solvers are not called."""
    rng = np.random.default_rng(k)
    x = rng.standard_normal((12, 12))
    a = x @ x.T + np.eye(12)
    bd = precond.BlockDiagonal(np.stack([a[i : i + k, i : i + k] for i in range(0, 12, k)]))
    want = np.sort(np.linalg.eigvals(bd(a)).real)
    monkeypatch.setattr(np.linalg, "eigvals", None)
    assert np.allclose(S.spectrum(a, bd), want) and np.allclose(S.spectrum(a), np.linalg.eigvalsh(a))


def test_explicit_matrix_by_blocks(spark, w0, monkeypatch):
    """Cells over chunk ends and cut slots equal the formed matrix; pairs are no rows."""
    from skyweave import registry
    from skyweave.operators import system

    tod, model, _ = w0
    monkeypatch.setattr(P, "band_pairs", None)
    gone = tod.withColumn("pix", F.when(F.col("pix") % 7 == 0, F.lit(-1).cast("long")).otherwise(F.col("pix")))
    op = NormalOperator(gone, model).form()
    at, a = {p: i for i, p in enumerate(op.pixels.tolist())}, np.zeros((op.n, op.n))
    got = system.explicit(gone, registry.kernel_rows(spark, model.kernels), 16, 20).collect()
    for r in got:
        a[at[r.p], at[r.q]] += r.v
    assert np.allclose(a, op.a, atol=1e-9) and len({(r.p, r.q) for r in got}) == len(got)


def test_same_noise_is_compared_by_tasks(spark):
    from skyweave import registry

    rows = [(k, t, float(k + t)) for k in range(2) for t in range(50)]
    one, far, less = (spark.createDataFrame(r, "interval_id long, t long, n double") for r in (rows, [(*rows[0][:2], 0.1), *rows[1:]], rows[1:]))
    assert registry.same_noise(one, one.repartition(3)) and not registry.same_noise(one, far) and not registry.same_noise(one, less) and not registry.same_noise(less, one)


def test_a_priori_span(w0):
    """More intervals than pixels: independent columns give the same preconditioner, merged ones equal merged hits."""
    _, _, op = w0
    h = op.hits()[1]
    assert np.allclose(op.hits_gram(), h @ h.T) and np.array_equal(op.hits_merged(3), precond.merge_columns(h, 3))
    z, bd, a = precond.a_priori(h), precond.BlockDiagonal(op.diagonal_blocks()), S.dense(op)
    u = precond.a_priori_span(op.hits_gram(), op.hits_merged(1)[:, 0])
    r = np.random.default_rng(0).standard_normal(op.n)
    one, two = (precond.two_level(bd, precond.Coarse(y, a @ y))(r) for y in (z, u))
    assert u.shape[1] == np.linalg.matrix_rank(z) and np.allclose(one, two, atol=1e-7)
    op.a = None


@pytest.mark.parametrize("nstokes", [1, 3])
def test_blocks_side_by_side_give_the_same_products(spark, nstokes):
    """Blocks of many lengths, with blind slots and halos, weighted together; and the matrix of short ones by lags."""
    rng = np.random.default_rng(5)
    rows = [(i, t, int(rng.integers(0, 9)) if t % 17 else -1, float(rng.random() * 3), float(rng.random()), i % 2) for i, n in enumerate((40, 41, 60, 150, 333, 900)) for t in range(n)]
    tod = spark.createDataFrame(rows, "interval_id long, t long, pix long, phi double, d double, noise_id int")
    model = K.Stationary({0: K.kernel(0.1, 16), 1: K.kernel(0.05, 16)})
    op = NormalOperator(tod, model, nstokes, 128)
    x = rng.standard_normal((op.n, 2))
    both = op.apply_many(x)  # block by block
    assert np.allclose(np.stack([op.apply(c) for c in x.T], axis=1), both)
    assert op.groups.count() < op.blocks.count()
    assert np.allclose(op.form().a @ x, both)
    op.close()


def test_packing_takes_samples_in_any_order(spark):
    """Samples come in order mostly; where they don't, tasks sort them, and no row is sorted by the exchange's own plan (before: a sort of every list)."""
    from skyweave.operators import system

    rng = np.random.default_rng(2)
    rows = [(i, t, int(rng.integers(-1, 5)), float(rng.random()), float(rng.random()), i % 2) for i, n in enumerate((7, 130, 64)) for t in range(n)]
    schema = "interval_id long, t long, pix long, phi double, d double, noise_id int"
    one, two = (system.pack(spark.createDataFrame([rows[k] for k in order], schema).coalesce(1), 16, 64) for order in (range(len(rows)), rng.permutation(len(rows)).tolist()))
    assert [tuple(r) for r in one.orderBy("interval_id", "chunk").collect()] == [tuple(r) for r in two.orderBy("interval_id", "chunk").collect()]
    assert "sort_array" not in one._jdf.queryExecution().toString()


def test_hits_come_from_grouped_blocks(spark):
    """Hits, the matrix and products need no more than the grouped blocks, and of these no data (before: the blocks' lists)."""
    rng = np.random.default_rng(6)
    rows = [(10 * i, t, int(rng.integers(0, 9)) if t % 17 else -1, float(rng.random() * 3), float(rng.random()), i % 2) for i, n in enumerate((40, 41, 150)) for t in range(n)]
    op = NormalOperator(spark.createDataFrame(rows, "interval_id long, t long, pix long, phi double, d double, noise_id int"), K.Stationary({0: K.kernel(0.1, 16), 1: K.kernel(0.05, 16)}), 3, 64)
    want = np.array([[sum(r[0] == i and r[2] == p for r in rows) for i in (0, 10, 20)] for p in op.pixels])
    x = rng.standard_normal((op.n, 2))
    both = op.apply_many(x)
    op.groups = op.groups.drop("d")
    op.work = None
    assert np.array_equal(op.hits()[1], want) and np.array_equal(op.hits_merged(2), precond.merge_columns(want, 2)) and np.allclose(op.hits_gram(), want @ want.T)
    assert np.allclose(op.apply(x[:, 0]), both[:, 0]) and np.allclose(op.form().a @ x, both)


def test_whole_scan_is_placed_without_a_table(spark, monkeypatch):
    """Samples of W2 as one interval keep their places in the total order; no table of all of them is written for that (before: one)."""
    from skyweave.plans import lineage

    monkeypatch.setattr(lineage, "cut", lambda df: pytest.fail("a table was written"))
    got = WL.tod_w2(spark, SF).select("t", "d").orderBy("t").toPandas()
    sql = f"SELECT o_totalprice AS d FROM '{SF}/orders.parquet' ORDER BY o_custkey % 32, year(o_orderdate), dayofyear(o_orderdate), o_orderkey"
    assert got["t"].tolist() == list(range(len(got))) and got["d"].tolist() == duckdb.sql(sql).df()["d"].tolist()


def test_cells_round_without_decimals(spark):
    """Cells of circles equal those of rounding to 9 digits, also where a point lies on an edge; Spark's round makes a decimal number of each (as before)."""
    grid = spark.range(3 * 366 * 64).select((F.col("id") % 366 + 1).alias("doy"), F.floor(F.col("id") / 366).alias("k"))
    angle, lon0 = F.col("doy") * (2 * math.pi / 366), F.col("k") * (2 * math.pi / 192)
    for radius, rows, cols in ((30.0, 32, 64), (7.5, 64, 128)):
        cell = WL.circle_pixel(angle, lon0, radius, rows, cols)
        r = math.radians(radius)
        turn = (lon0 + F.atan2(F.sin(angle) * math.sin(r), F.lit(math.cos(r)))) / (2 * math.pi)
        turn = turn - F.floor(F.round(turn, 9))
        want = F.floor(F.round((F.lit(math.sin(r)) * F.cos(angle) + 1) / 2 * rows, 9)) * cols + F.pmod(F.floor(F.round(turn * cols, 9)), F.lit(cols))
        assert grid.where(cell != want).count() == 0
        assert "round(" not in grid.select(cell)._jdf.queryExecution().toString()


def test_other_models_share_blocks(w0):
    wide, narrow = K.Stationary({0: K.kernel(0.05, 128), 1: K.kernel(0.1, 128)}), K.Stationary({0: K.kernel(0.05, 32), 1: K.kernel(0.1, 32)})
    op, own = NormalOperator(w0[0], wide, 1, 64), NormalOperator(w0[0], narrow, 1, 64)
    some = op.other(narrow)
    assert np.allclose(some.rhs(), own.rhs()) and np.allclose(some.form().a, own.form().a) and op.a is None
    assert np.allclose(some.diagonal_blocks(), own.diagonal_blocks())
    with pytest.raises(ValueError):
        own.other(wide)
    op.close(), own.close()


def test_solvers_agree(w0):
    tod, model, op = w0
    b = op.rhs()
    ref = S.direct(op, b)
    for how in ({"prec": "bd"}, {"prec": "none"}, {"prec": "apriori"}, {"prec": "aposteriori"}, {"prec": "deflation", "rank": 3}, {"prec": "apriori", "variant": "def2"}, {"solver": "gmres"}):
        run = S.make_map(tod, model, op=op, b=b, tol=1e-11, **how)
        assert np.allclose(run.solution.x, ref, atol=1e-7), how
    x, took = S.solve_many(op, precond.BlockDiagonal(op.diagonal_blocks()), np.stack((b, 2 * b), axis=1), 1e-11)
    assert np.allclose(x[:, 1], 2 * ref, atol=1e-6) and took.max() < 100


def test_krylov_relations(w0):
    _, _, op = w0
    a, bd = S.dense(op), precond.BlockDiagonal(op.diagonal_blocks())
    apply = lambda v: bd(a @ v)
    w, h = krylov.arnoldi(apply, np.random.default_rng(2).standard_normal(op.n), 6)
    m = h.shape[1]
    assert np.allclose(np.stack([apply(q) for q in w[:, :m].T], axis=1), w[:, : h.shape[0]] @ h, atol=1e-10)
    r = krylov.ritz(w, h)
    for k in range(m):
        res = apply(r.vectors[:, k].real) + 1j * apply(r.vectors[:, k].imag) - r.values[k] * r.vectors[:, k]
        assert np.isclose(np.linalg.norm(res), r.error[k], atol=1e-8)
    az = precond.az_from_arnoldi(lambda v: np.linalg.solve(np.stack([bd(e) for e in np.eye(op.n)], axis=1), v), w, h, np.eye(m))
    assert np.allclose(az, a @ w[:, :m])


def test_white_noise_converges_at_once(spark):
    tod = WL.tod_w0(spark, SF)
    run = S.make_map(tod, K.Stationary({0: K.white_kernel(), 1: K.white_kernel()}))
    assert run.solution.iterations == 1
    co = {r.pix: r.i for r in P.coadd(tod).collect()}
    assert np.allclose(run.solution.x, [co[p] for p in run.op.pixels.tolist()])


def test_bound_holds():
    rng = np.random.default_rng(5)
    q, _ = np.linalg.qr(rng.standard_normal((30, 30)))
    a = q @ np.diag(np.linspace(1, 50, 30)) @ q.T
    ref, errs = rng.standard_normal(30), []
    b = a @ ref
    for j in range(1, 15):
        s = krylov.cg(lambda v: a @ v, precond.identity(), b, tol=0, max_iter=j, strict=False)
        errs.append(S.a_norm_error(a, s.x, ref))
    e0, k = S.a_norm_error(a, 0 * ref, ref), math.sqrt(50)
    assert all(e <= e0 * 2 * ((k - 1) / (k + 1)) ** j * 1.0001 for j, e in enumerate(errs, 1))


def test_failures(spark):
    with pytest.raises(krylov.NonConvergence):
        krylov.cg(lambda v: -v, precond.identity(), np.ones(3))
    with pytest.raises(np.linalg.LinAlgError):
        precond.BlockDiagonal(np.zeros((2, 3, 3)))
    s = krylov.cg(lambda v: v, precond.identity(), np.zeros(3))
    assert s.converged and s.iterations == 0
    s = krylov.cg(lambda v: v, precond.identity(), np.ones(3), x0=np.ones(3))
    assert s.converged and s.iterations == 0


def test_cut_slots_keep_true_lags(spark):
    """A cut map equals the dense solution with the lags that the samples have; moving samples up does not."""
    rng = np.random.default_rng(4)
    n, w = 60, K.kernel(0.1, 16)
    pix, phi = rng.integers(0, 4, n), rng.integers(0, 4, n) * math.pi / 4
    pix[[7, 8, 9, 30]] = 9  # seen at one angle only
    phi[[7, 8, 9, 30]] = 0
    d = rng.standard_normal(n)
    tod = spark.createDataFrame([(0, t, int(pix[t]), float(phi[t]), float(d[t]), 0) for t in range(n)], "interval_id long, t long, pix long, phi double, d double, noise_id int")
    model, full = K.Stationary({0: w}), dense_weights(w, n)
    cut, gone = P.pixel_cut(tod)
    assert [r.pix for r in gone.collect()] == [9]
    p = np.zeros((n, 12))
    for t in np.flatnonzero(pix != 9):
        p[t, 3 * pix[t] : 3 * pix[t] + 3] = 1, math.cos(2 * phi[t]), math.sin(2 * phi[t])
    want = np.linalg.solve(p.T @ full @ p, p.T @ full @ np.where(pix == 9, 0, d))
    for length in (1 << 20, 10):
        run = S.make_map(cut, model, 3, tol=1e-12, length=length)
        assert run.op.pixels.tolist() == [0, 1, 2, 3] and np.allclose(run.solution.x, want, atol=1e-8)
    assert run.op.hits()[1].sum() == n - 4
    far = S.distributed_cg(DistributedOperator(cut, model, 3, length=25), 1e-11)[0].orderBy("pix").collect()
    assert np.allclose([[r.i, r.q, r.u] for r in far], want.reshape(4, 3), atol=1e-6)
    closed = S.make_map(P.pixel_cut(tod, gap="close")[0], model, 3, tol=1e-12)
    assert not np.allclose(closed.solution.x, want, atol=1e-3)
    kept = np.flatnonzero(pix != 9)
    piece = np.cumsum(np.diff(kept, prepend=kept[0]) > 1)
    split = full[np.ix_(kept, kept)] * (piece[:, None] == piece[None, :])
    want = np.linalg.solve(p[kept].T @ split @ p[kept], p[kept].T @ split @ d[kept])
    assert np.allclose(S.make_map(P.pixel_cut(tod, gap="split")[0], model, 3, tol=1e-12).solution.x, want, atol=1e-8)
    filled = P.fill_gaps(tod.where("pix <> 9"))
    assert filled.count() == n and filled.where("pix = -1").count() == 4
    assert np.allclose(S.make_map(filled, model, 3, tol=1e-12).solution.x, run.solution.x, atol=1e-8)


def test_distributed_coarse_space(w0):
    """Z, A Z, E and the preconditioner by tables equal those on the driver."""
    _, model, op = w0
    d = DistributedOperator(WL.tod_w0(op.spark, SF).cache(), model, length=10)
    rank = 4
    interval, hits = op.hits()
    z = precond.a_priori(hits)
    mine = np.stack([z[:, interval % rank == k].sum(axis=1) for k in range(rank)], axis=1)
    az, t = np.zeros_like(mine), S.Tables(d, rank)
    at = {p: i for i, p in enumerate(op.pixels.tolist())}
    for r in d.apply_coarse(d.a_priori(rank)).collect():
        az[at[r.pix], r.col] = r.v0
    c = precond.Coarse(mine, op.apply_many(mine))
    assert np.allclose(az, c.az) and np.allclose(t.e, c.e)
    v = np.random.default_rng(1).standard_normal(op.n)
    two = precond.two_level(precond.BlockDiagonal(op.diagonal_blocks()), c)
    rows = op.spark.createDataFrame([(p, float(v[i])) for p, i in at.items()], "pix long, r0 double")
    got = {r.pix: r.m0 for r in t.apply(rows, ["r0"]).collect()}
    assert np.allclose(two(v), [got[p] for p in op.pixels.tolist()])
    with pytest.raises(ValueError):
        S.Tables(d, 10**6)


def test_plan_counts_the_coarse_space(w0):
    tod, model, op = w0
    assert strategy.choose(10**6, 3, 2048).kind == "shuffle" and strategy.choose(10**6, 3).kind == "broadcast"
    with pytest.raises(ValueError, match="DistributedOperator"):
        NormalOperator(tod, model, budget=1)
    with pytest.raises(ValueError, match="driver"):
        S.solve_map(tod, model, prec="aposteriori", budget=1)
    a, b = (S.solve_map(tod, model, prec="apriori", rank=3, tol=1e-10, budget=n).orderBy("pix").toPandas() for n in (None, 1))
    assert np.allclose(a.i, b.i, atol=1e-7)


def test_simulated_samples(spark):
    from skyweave.sources import simulate

    tod = WL.tod_w0(spark, SF)
    one, two = (simulate.noise(t, {0: 0.05, 1: 0.1}, length=n).orderBy("interval_id", "t").toPandas() for t, n in ((tod, 1 << 20), (tod.repartition(3, "t"), 60)))
    assert len(one) == tod.count() and np.allclose(one.n, two.n, atol=1e-10)
    w = simulate.colour_kernel(0.0, 4.0)
    assert np.isclose(w[0], 2) and np.allclose(w[1:], 0, atol=1e-12)
    f = np.fft.rfft(np.concatenate((simulate.colour_kernel(0.1), simulate.colour_kernel(0.1)[-2:0:-1]))).real
    assert np.allclose(f[1:] ** 2, 1 + (0.1 / (np.arange(1, 513) / 1024)) ** 2)


def test_scaling_packs_each_number_of_circles_once(spark, w0):
    tod, model, _ = w0
    asked = []
    rows = S.scalings(spark, lambda n: asked.append(n) or tod.where(f"interval_id < {n}"), model, [4, 4], [1, 2], {"bd": {}, "apriori": {"rank": 2}})
    assert asked == [4] and [r[:3] for r in rows] == [("bd", 4, 1), ("bd", 4, 2), ("apriori", 4, 1), ("apriori", 4, 2)]
    assert rows[0][3] == tod.where("interval_id < 4").count() and rows[0][4] == rows[1][4] and rows[2][4] == rows[3][4]


def test_scaling_and_breakdown(spark, w0):
    tod, model, op = w0
    rows = S.scaling(spark, lambda n: tod.where(f"interval_id < {n}"), model, [2, 4], [1, 2])
    assert [r[:2] for r in rows] == [(2, 1), (4, 2)] and rows[0][2] < rows[1][2] and all(r[3] > 0 for r in rows)
    t = S.breakdown(op, None, precond.BlockDiagonal(op.diagonal_blocks()), 1)
    assert np.isclose(t["product"], t["noise_weighting"] + t["accumulate_reduce"])


def test_blocks_and_maps_are_written_and_read(spark, w0, tmp_path):
    from skyweave.operators import system

    _, _, op = w0
    system.save(op.blocks, str(tmp_path / "blocks"))
    back = system.load(spark, str(tmp_path / "blocks"))
    assert sorted(r.interval_id for r in back.collect()) == sorted(r.interval_id for r in op.blocks.collect())
    assert system.load(spark, str(tmp_path / "blocks"), 2).select("interval_id").distinct().count() <= 2


SMALL = ["white_weight_w0", "band_rules", "pixel_cut_slots_w3", "pixel_cut_split_w3", "zs_polarised", "map_w4_fourier", "map_w5_full_block", "flagship_map_w0", "map_w0_apriori", "hit_map_w0", "hit_map_w2", "tod_index_w1", "noise_weight_lagjoin_w0", "noise_weight_fir_w0", "noise_weight_fft_w0", "rhs_w0", "system_matrix_w0", "az_w0", "bd_inverse_pol", "coadd_pol", "zs_merged_r10", "asof_pointing", "interval_assign", "pixel_cut_anti_w3", "map_rebin_cube", "stream_coadd", "stream_daily", "kernel_apodized", "unbiased_noise_free", "scan_source", "udtf_kernel_lags", "udtf_small_map_w4", "stream_sessions", "stream_near_pointing", "stream_interval_close", "stream_unique_hits"]


FROM_TABLES = ["apodized_spectrum", "deflection_freq", "inverse_psd_table", "kappa_bound", "kernel_hardcut", "psd_table"]


@pytest.mark.parametrize("name", ["apodisation_study", "band_rules", "kernel_apodized", "scan_source", "udtf_kernel_lags", *FROM_TABLES])
def test_query_reads_a_table(spark, name):
    plan = entry.queries()[name](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert "parquet" in plan


@pytest.mark.parametrize("name", SMALL + FROM_TABLES)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    want = con.sql(entry.oracle_sql()[name]).df()
    got = entry.queries()[name](spark, SF).toPandas()
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols and len(got) == len(want)
    key = lambda f: list(tuple(None if x != x or x is None else round(float(x), 4) for x in r) for r in f[cols].astype(object).where(f[cols].notna(), None).values.tolist())
    a, b = (sorted(k, key=str) for k in (key(got), key(want)))
    assert all((x is None and y is None) or abs(x - y) < 2e-3 for r, s in zip(a, b) for x, y in zip(r, s))


def test_scan_source(spark):
    from skyweave.sources.scan import scan

    whole, cut = (scan(spark, circles=2, rescans=2, samples=50, chunk=c) for c in (1000, 30))
    assert cut.rdd.getNumPartitions() == 8 and sorted(map(tuple, cut.collect())) == sorted(map(tuple, whole.collect()))
    assert whole.groupBy("interval_id").count().where("count <> 100").count() == 0
    with pytest.raises(ValueError):
        scan(spark, circle=2)


def test_small_map_partitions(spark):
    from skyweave.functions import tables

    rows = [(k, 0, t, t % 3, float(k + t % 3)) for k in (1, 2) for t in range(30)]
    df = spark.createDataFrame(rows, "key int, interval_id long, t long, pix long, d double")
    got = tables.small_map(df.asTable().partitionBy("key"), *map(spark_lit, (0.0, 0))).collect()
    assert sorted((r.pix, round(r.i, 9)) for r in got) == [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3), (2, 4)]
    gaps = df.where("key = 1 and t <> 5")
    with pytest.raises(Exception, match="gaps"):
        tables.small_map(gaps.asTable().withSinglePartition(), *map(spark_lit, (0.1, 4))).collect()


def spark_lit(x):
    from pyspark.sql import functions as F

    return F.lit(x)


@pytest.mark.parametrize("name, polarisers", [("convergence_by_circles", ["none", "fast"]), ("convergence_medium", ["medium"]), ("convergence_slow", ["slow"])])
def test_convergence_takes_every_circle(spark, monkeypatch, name, polarisers):
    """The first point of each polariser has all rows of the table, four times for the slow one; the solves are left out."""
    from skyweave import registry

    seen = []
    monkeypatch.setattr(registry.P, "pixel_cut", lambda tod: (tod,))
    monkeypatch.setattr(registry.WL, "tod_w3", lambda s, d, pol, n, f=WL.tod_w3: seen.append((pol, n, f(s, d, pol, n))) or seen[-1][2])
    monkeypatch.setattr(registry.Y, "NormalOperator", lambda *a: type("Nothing", (), {"close": lambda self: None})())
    monkeypatch.setattr(registry, "_both", lambda op: [])
    entry.queries()[name](spark, SF)
    n, circles = spark.read.parquet(f"{SF}/lineitem.parquet").count(), spark.read.parquet(f"{SF}/supplier.parquet").count()
    whole = [(pol, tod) for pol, most, tod in seen if most is None]
    assert [pol for pol, _ in whole] == polarisers
    for pol, tod in whole:
        times = 4 if pol == "slow" else 1
        assert tod.count() == n * times and tod.select("interval_id").distinct().count() == circles * times


@pytest.mark.parametrize("name", ["history_holds_w0", "many_rhs_holds_w0"])
def test_facts(spark, name):
    got = entry.queries()[name](spark, SF).collect()
    con = duckdb.connect()
    assert sorted((r.fact, r.ok) for r in got) == sorted(con.sql(entry.oracle_sql()[name]).fetchall())


def test_late_samples_by_batch(spark, tmp_path):
    """Batches in file order: what lies behind the greatest earlier time less the delay is late, and a rerun adds nothing."""
    import datetime
    import os

    from skyweave.streaming import maps

    start = datetime.datetime(2024, 1, 1)
    for k, hours in enumerate(([0, 1, 5], [4.5, 3.9, 6], [4.9, 5.0, 0.1, 7], [])):
        rows = [(i, start + datetime.timedelta(hours=h)) for i, h in enumerate(hours)]
        spark.createDataFrame(rows, "sample_id long, ts timestamp").coalesce(1).write.parquet(str(tmp_path / f"in/b={k}"))
        for name in os.listdir(tmp_path / f"in/b={k}"):
            os.utime(tmp_path / f"in/b={k}" / name, (1e9 + k, 1e9 + k))
    for _ in range(2):
        stream = spark.readStream.schema("sample_id long, ts timestamp, b int").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
        got = sorted(map(tuple, maps.late_samples(stream, str(tmp_path / "out")).select("batch", "n", "late").collect()))
        assert got[:3] == [(0, 3, 0), (1, 3, 1), (2, 4, 2)] and sum(r[1] for r in got) == 10


def _block_rows(blocks):
    return sorted(tuple(tuple(x) if isinstance(x, list) else x for x in r) for r in blocks.collect())


@pytest.mark.parametrize("halo,length", [(256, 1 << 20), (16, 40), (None, 1 << 20)])
def test_circles_in_order_by_their_tasks_are_the_blocks_of_sorted_ones(spark, monkeypatch, halo, length):
    want = _block_rows(system.pack(WL.tod_w3(spark, SF), halo, length))
    monkeypatch.setattr(arrange, "SENT", 1000)
    monkeypatch.setattr(arrange, "DEALT", 500)
    scan = WL.unplaced_w3(spark, SF)
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key)
    with scan.planned():
        got = _block_rows(scan.pack(halo, length, 3))
    assert got == want and spark.conf.get(key) == before
    monkeypatch.setattr(arrange, "LONGEST", 10)  # Spark sorts longer ones
    assert _block_rows(scan.pack(halo, length, 3)) == want


def test_order_of_samples_with_ties_and_nulls(spark):
    rng = np.random.default_rng(8)
    columns = [rng.integers(-3, 3, 500), rng.integers(-5, 5, 500), rng.integers(0, 4, 500), rng.integers(0, 3, 500) / 4.0]
    for some in (columns, [columns[0] * (1 << 60), *columns[1:]]):
        assert np.array_equal(*(np.stack(some)[:, order] for order in (arrange.arranged(some), np.lexsort(some[::-1]))))
    rows = spark.createDataFrame([(1, 5, 7, 1.0), (1, 5, None, 2.0), (1, 5, -(1 << 40), 3.0), (1, 4, 9, None), (2, 0, 0, 4.0)], "interval_id long, day int, k long, d double")
    scan = arrange.Unplaced(rows, ("day", "k", "d"), lambda i, c: (np.arange(len(i)) * 0, np.zeros(len(i)), c[-1], i % 2), lambda: None)
    (_, a), (_, b) = sorted((r["interval_id"], r["d"]) for r in scan.pack(4, 100, 2).collect())
    assert math.isnan(a[0]) and a[1:] == [2.0, 3.0, 1.0] and b == [4.0]
    with pytest.raises(Exception, match="no interval or no day"):
        arrange.Unplaced(rows.withColumn("day", F.lit(None).cast("int")), ("day", "k", "d"), scan.place, scan.tod).pack(4, 100, 2).collect()


@pytest.mark.parametrize("nstokes", [1, 3])
def test_several_dense_columns_are_taken_by_grouped_blocks(spark, nstokes):
    rows = [(i, t, (3 * t + i) % 7, 0.3 * t * (i + 1), float(t), i % 2) for i in range(5) for t in range(60)]
    op = NormalOperator(spark.createDataFrame(rows, "interval_id long, t long, pix long, phi double, d double, noise_id int"), K.Stationary({0: K.kernel(0.1, 16), 1: K.kernel(0.05, 16)}), nstokes, 32)
    x = np.random.default_rng(2).standard_normal((op.n, 3))
    want = np.stack([op.apply(c) for c in x.T], axis=1)
    assert np.allclose(op.apply_many(x, sparse=True), want, atol=1e-9) and np.allclose(op.form().a @ x, want, atol=1e-9)
    op.a, op.blocks = None, None  # the blocks themselves are not read again
    assert np.allclose(op.apply_many(x), want, atol=1e-9) and op.intervals().tolist() == [0, 1, 2, 3, 4]


@pytest.mark.parametrize("nstokes, length, model", [(1, 1 << 20, "band"), (1, 10, "band"), (3, 10, "band"), (1, 1 << 20, "modes")])
def test_matrix_in_bands(spark, monkeypatch, nstokes, length, model):
    """A matrix that is not for the driver is made and kept by tasks; products, solution and spectra are those of the matrix on the driver."""
    model = K.Stationary({k: K.kernel(0.05 * (k + 1), 16) for k in (0, 1)}) if model == "band" else K.Circulant({0: 0.1, 1: 0.05}, lowest=0.5)
    tod = WL.tod_w0(spark, SF, nstokes == 3)
    tod = P.pixel_cut(tod)[0] if nstokes == 3 else tod
    op = NormalOperator(tod, model, nstokes, length)
    b, bd = op.rhs(), precond.BlockDiagonal(op.diagonal_blocks())
    z = precond.a_priori(op.hits_merged(3), nstokes)
    z = np.concatenate((z, z[:, :1]), axis=1)  # one column is dropped
    monkeypatch.setattr(system, "BAND", 8 * nstokes * op.n * 2)
    monkeypatch.setattr(S, "DENSE", 1)
    bands = S.dense(op)
    assert isinstance(bands, system.Bands) and op.a is None and S.dense(op) is bands
    want = op.form().a
    eye = np.eye(op.n)
    cells = bands.whole([np.tril, lambda a: a])
    assert np.allclose(cells[0], np.tril(want).ravel(), atol=1e-9) and np.allclose(bands @ eye, want, atol=1e-9) and np.allclose(b @ bands, b @ want) and np.allclose(bands @ b, want @ b)
    c = precond.Coarse(z, bands @ z)
    forms = [None, bd, precond.two_level(bd, c), precond.two_level(bd, c, "def2")]
    got = S.spectra(bands, forms)
    assert all(np.allclose(v, S.spectrum(want, f), atol=1e-8) for v, f in zip(got, forms))
    assert (np.abs(got[2] - 1) < 1e-8).sum() >= 3 and np.allclose(S.solved(bands, b), np.linalg.solve(want, b))
    op.close()


def test_matrix_beyond_a_task_is_refused(spark, w0, monkeypatch):
    _, model, _ = w0
    op = NormalOperator(WL.tod_w0(spark, SF), model)
    monkeypatch.setattr(S, "DENSE", 1)
    monkeypatch.setattr(system, "ROOM", 8 * op.n * op.n - 1)
    with pytest.raises(ValueError, match="more than the"):
        S.direct(op)
    op.close()


def test_direct_map_and_spectra_by_tasks(spark, monkeypatch):
    """The queries give the same rows where their matrix is not for the driver, which then has no array of that size."""
    want = {q: [tuple(r) for r in entry.queries()[q](spark, SF).collect()] for q in ("map_w0_direct", "spectrum_w0")}
    monkeypatch.setattr(S, "DENSE", 1)
    monkeypatch.setattr(NormalOperator, "_formed", None)
    for q, rows in want.items():
        got = [tuple(r) for r in entry.queries()[q](spark, SF).collect()]
        assert len(got) == len(rows) and all(g[:-2] == w[:-2] and np.allclose(g[-2:], w[-2:], rtol=1e-6, atol=1e-6) for g, w in zip(got, rows))
    for q in ("krylov_holds_w0", "spectrum_holds_w0"):
        assert all(r["ok"] for r in entry.queries()[q](spark, SF).collect()), q
