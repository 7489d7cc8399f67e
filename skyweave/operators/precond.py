"""Preconditioners: none, the standard per-pixel blocks, deflation, and the two two-level forms, with their coarse spaces."""

from __future__ import annotations

import numpy as np

from skyweave.operators import krylov


def identity():
    return lambda r: r


class BlockDiagonal:
    """Inverse of P' diag(W) P: one small dense block per pixel."""

    def __init__(self, blocks: np.ndarray, rcond: float = 1e-10):
        e = np.linalg.eigvalsh(blocks)
        if len(e) and (e[:, 0] <= rcond * e[:, -1]).any():
            raise np.linalg.LinAlgError(f"{int((e[:, 0] <= rcond * e[:, -1]).sum())} pixels have a singular Stokes block; apply pixel_cut first")
        self.inverse = np.linalg.inv(blocks)

    def __call__(self, r: np.ndarray) -> np.ndarray:
        n, s, _ = self.inverse.shape
        return np.einsum("pij,pj...->pi...", self.inverse, r.reshape(n, s, *r.shape[1:])).reshape(r.shape)


class Coarse:
    """E = Z' A Z with a rank-revealing inverse; dependent columns of Z are dropped."""

    def __init__(self, z: np.ndarray, az: np.ndarray, drop: float = 1e-12):
        self.z, self.az = z, az
        self.e = (z.T @ az + az.T @ z) / 2
        d, v = np.linalg.eigh(self.e)
        keep = d > drop * max(d.max(), 0.0)
        self.rank_dropped, self.kept = int((~keep).sum()), v[:, keep]
        self.inverse = (v[:, keep] / d[keep]) @ v[:, keep].T

    def solve(self, r):
        return self.inverse @ (self.z.T @ r)


def deflation(coarse: Coarse):
    """R = I - A Z E^-1 Z' alone."""
    return lambda r: r - coarse.az @ coarse.solve(r)


class TwoLevel:
    """def1: BD R + Z E^-1 Z'. def2: R' BD + Z E^-1 Z', which needs two coarse solves per application."""

    def __init__(self, bd, coarse: Coarse, variant: str = "def1"):
        if variant not in ("def1", "def2"):
            raise ValueError(f"unknown variant {variant!r}")
        self.bd, self.coarse, self.variant = bd, coarse, variant

    def __call__(self, r: np.ndarray) -> np.ndarray:
        coarse = self.coarse
        if self.variant == "def1":
            c = coarse.solve(r)
            return self.bd(r - coarse.az @ c) + coarse.z @ c
        y = self.bd(r)
        return y - coarse.z @ (coarse.inverse @ (coarse.az.T @ y)) + coarse.z @ coarse.solve(r)


def two_level(bd, coarse: Coarse, variant: str = "def1") -> TwoLevel:
    return TwoLevel(bd, coarse, variant)


def def2_start(b: np.ndarray, coarse: Coarse, x_bar: np.ndarray | None = None) -> np.ndarray:
    """Start vector of variant 2: the coarse part of the solution is exact from the first step on."""
    x = np.zeros_like(b) if x_bar is None else x_bar
    return coarse.z @ coarse.solve(b) + x - coarse.z @ (coarse.inverse @ (coarse.az.T @ x))


def a_priori(hits: np.ndarray, nstokes: int = 1) -> np.ndarray:
    """Column j: the share of a pixel's hits that interval j made, in the intensity rows; zero in the others."""
    z = np.zeros((hits.shape[0], nstokes, hits.shape[1]))
    z[:, 0, :] = hits / hits.sum(axis=1, keepdims=True)
    return z.reshape(-1, hits.shape[1])


def a_priori_span(gram: np.ndarray, hits: np.ndarray, nstokes: int = 1, drop: float = 1e-12) -> np.ndarray:
    """Orthonormal columns that span all a-priori columns, from H H' for the (n_pix, K) hits H and their sums by pixel. The preconditioners depend on
    that span alone, which has at most n_pix dimensions, however many intervals there are."""
    values, v = np.linalg.eigh(gram / np.outer(hits, hits))
    u = v[:, values > drop * values.max()]
    z = np.zeros((len(hits), nstokes, u.shape[1]))
    z[:, 0, :] = u
    return z.reshape(-1, u.shape[1])


def merge_columns(z: np.ndarray, r: int, how: str = "contiguous") -> np.ndarray:
    """r columns by adding columns; row sums stay."""
    k = z.shape[1]
    to = np.arange(k) * r // k if how == "contiguous" else np.arange(k) % r
    out = np.zeros((z.shape[0], r))
    for j in range(k):
        out[:, to[j]] += z[:, j]
    return out


def ones(n_pix: int, nstokes: int = 1) -> np.ndarray:
    z = np.zeros((n_pix, nstokes, 1))
    z[:, 0, 0] = 1
    return z.reshape(-1, 1)


def select(r: krylov.Ritz, eps_tol: float | None = None, dim: int | None = None) -> np.ndarray:
    """Real orthonormal columns that span the Ritz vectors with |Re value| < eps_tol, or of the ``dim`` smallest."""
    size = np.abs(r.values.real)
    pick = np.arange(len(size)) if eps_tol is None else np.flatnonzero(size < eps_tol)
    pick = pick[np.argsort(size[pick])][:dim]
    if not len(pick):
        return np.empty((r.vectors.shape[0], 0))
    y = r.vectors[:, pick]
    both = np.concatenate((y.real, y.imag), axis=1)
    both = both[:, np.linalg.norm(both, axis=0) > 1e-12]
    u, d, _ = np.linalg.svd(both / np.linalg.norm(both, axis=0), full_matrices=False)
    return u[:, d > 1e-8 * d[0]]


def a_posteriori(apply, bd, b_prev, eps_tol: float | None = 0.2, max_dim: int | None = None, m_max: int = 200, tol: float = 1e-6):
    """Coarse space learnt from an earlier solve with the standard preconditioner; also whether that solve converged."""
    s, w, h = krylov.gmres(apply, bd, b_prev, tol, m_max)
    return select(krylov.ritz(w, h), eps_tol, max_dim), s


def update(z: np.ndarray, apply, bd, r: krylov.Ritz, eps_tol: float, max_dim: int) -> np.ndarray:
    """Join an old coarse space with a new run's Ritz vectors, keeping the ``max_dim`` lowest directions of BD A in their span."""
    both = np.concatenate((z, select(r, eps_tol)), axis=1)
    u, d, _ = np.linalg.svd(both, full_matrices=False)
    q = u[:, d > 1e-8 * d[0]]
    values, v = np.linalg.eig(q.T @ np.stack([bd(apply(c)) for c in q.T], axis=1))
    order = np.argsort(np.abs(values.real))[:max_dim]
    span = np.concatenate(((q @ v[:, order]).real, (q @ v[:, order]).imag), axis=1)
    u, d, _ = np.linalg.svd(span, full_matrices=False)
    return u[:, d > 1e-8 * d[0]][:, :max_dim]


def az_from_arnoldi(bd_inverse, w: np.ndarray, h: np.ndarray, coefficients: np.ndarray) -> np.ndarray:
    """A Z for Z = W_m V without another pass over the data: BD A W_m = W_{m+1} H."""
    return bd_inverse(w[:, : h.shape[0]] @ (h @ coefficients))
