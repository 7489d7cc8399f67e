"""Krylov solvers on driver vectors: preconditioned CG, Arnoldi, GMRES, Ritz pairs."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np


class NonConvergence(RuntimeError):
    def __init__(self, message: str, history):
        super().__init__(message)
        self.history = history


@dataclass
class Solution:
    x: np.ndarray
    history: list[tuple[int, float, float]]
    converged: bool
    true_residual: float = float("nan")
    alphas: list[float] = field(default_factory=list)
    betas: list[float] = field(default_factory=list)
    basis: list[np.ndarray] = field(default_factory=list)
    z_norms: list[float] = field(default_factory=list)

    @property
    def iterations(self) -> int:
        return self.history[-1][0]


def cg(apply, prec, b, x0=None, tol: float = 1e-6, max_iter: int = 2000, beta: str = "standard", keep_basis: bool = False, strict: bool = True) -> Solution:
    """Preconditioned CG. ``beta="flexible"`` suits preconditioners that are not symmetric; a lost sign is an error, never a silent switch."""
    x = np.zeros_like(b) if x0 is None else x0.copy()
    r = b - apply(x) if x0 is not None else b.copy()
    norm = np.linalg.norm(b)
    began = time.perf_counter()
    out = Solution(x, [(0, float(np.linalg.norm(r) / norm) if norm else 0.0, 0.0)], False)
    if norm == 0 or out.history[0][1] <= tol:
        out.converged, out.true_residual = True, out.history[0][1]
        return out
    z = prec(r)
    p, rz = z.copy(), r @ z
    for i in range(1, max_iter + 1):
        if keep_basis:
            out.basis.append(z.copy())
            out.z_norms.append(float(rz))
        q = apply(p)
        pq = p @ q
        if pq <= 0 or rz <= 0:
            raise NonConvergence(f"iteration {i}: p'Ap = {pq:.3g}, r'z = {rz:.3g}; the system or preconditioner is not positive here", out.history)
        alpha = rz / pq
        x += alpha * p
        r_old = r.copy() if beta == "flexible" else None
        r -= alpha * q
        out.alphas.append(float(alpha))
        rel = float(np.linalg.norm(r) / norm)
        out.history.append((i, rel, time.perf_counter() - began))
        if rel <= tol:
            out.converged = True
            break
        z = prec(r)
        new = r @ z
        step = (new - z @ r_old) / rz if beta == "flexible" else new / rz
        out.betas.append(float(step))
        p, rz = z + step * p, new
    out.true_residual = float(np.linalg.norm(b - apply(x)) / norm)
    if strict and not out.converged:
        raise NonConvergence(f"{max_iter} iterations, residual {out.history[-1][1]:.3g}", out.history)
    return out


def arnoldi(apply, start: np.ndarray, m: int, reorth: bool = True, stop=None) -> tuple[np.ndarray, np.ndarray]:
    """Orthonormal basis (n, j + 1) and Hessenberg matrix (j + 1, j); fewer columns on breakdown or when stop(H) says so."""
    w = [start / np.linalg.norm(start)]
    h = np.zeros((m + 1, m))
    for j in range(m):
        v = apply(w[j])
        size = np.linalg.norm(v)
        basis = np.stack(w, axis=1)
        for _ in range(2 if reorth else 1):
            c = basis.T @ v
            h[: j + 1, j] += c
            v = v - basis @ c
        h[j + 1, j] = np.linalg.norm(v)
        if h[j + 1, j] <= 1e-13 * max(size, 1e-300):
            h[j + 1, j] = 0.0
            return basis, h[: j + 1, : j + 1]
        w.append(v / h[j + 1, j])
        if stop is not None and stop(h[: j + 2, : j + 1]):
            return np.stack(w, axis=1), h[: j + 2, : j + 1]
    return np.stack(w, axis=1), h


def gmres(apply, prec, b, tol: float = 1e-6, m_max: int = 200) -> tuple[Solution, np.ndarray, np.ndarray]:
    """Left-preconditioned GMRES without restart; also gives the Krylov basis and Hessenberg matrix."""
    began = time.perf_counter()
    z = prec(b)
    size = np.linalg.norm(z)
    if size == 0:
        return Solution(np.zeros_like(b), [(0, 0.0, 0.0)], True, 0.0), np.empty((len(b), 0)), np.empty((0, 0))
    history = [(0, 1.0, 0.0)]

    def solve(h):
        e = np.zeros(h.shape[0])
        e[0] = size
        y, *_ = np.linalg.lstsq(h, e, rcond=None)
        return y, float(np.linalg.norm(e - h @ y) / size)

    def stop(h):
        history.append((h.shape[1], solve(h)[1], time.perf_counter() - began))
        return history[-1][1] <= tol

    w, h = arnoldi(lambda v: prec(apply(v)), z, m_max, stop=stop)
    y, rel = solve(h)
    if h.shape[1] > history[-1][0]:
        history.append((h.shape[1], rel, time.perf_counter() - began))
    x = w[:, : h.shape[1]] @ y
    return Solution(x, history, rel <= tol, float(np.linalg.norm(b - apply(x)) / np.linalg.norm(b))), w, h


@dataclass
class Ritz:
    values: np.ndarray
    vectors: np.ndarray  # of the full space, one column per value
    error: np.ndarray


def ritz(w: np.ndarray, h: np.ndarray) -> Ritz:
    """Ritz pairs of the square part of h, and |h_{m+1,m} v_m| as their residual norms."""
    m = h.shape[1]
    values, v = np.linalg.eig(h[:m, :m])
    last = h[m, m - 1] if h.shape[0] > m else 0.0
    order = np.argsort(np.abs(values.real))
    return Ritz(values[order], w[:, :m] @ v[:, order], np.abs(last * v[m - 1, order]))


def ritz_from_cg(s: Solution) -> Ritz:
    """Ritz pairs of the preconditioned system from CG coefficients (Lanczos tridiagonal); needs keep_basis."""
    a, b = np.array(s.alphas), np.array(s.betas)
    m = min(len(a), len(s.basis))
    t = np.zeros((m, m))
    for i in range(m):
        t[i, i] = 1 / a[i] + (b[i - 1] / a[i - 1] if i else 0.0)
        if i + 1 < m:
            t[i, i + 1] = t[i + 1, i] = np.sqrt(b[i]) / a[i]
    values, v = np.linalg.eigh(t)
    q = np.stack([(-1) ** i * s.basis[i] / np.sqrt(s.z_norms[i]) for i in range(m)], axis=1)
    last = np.sqrt(b[m - 1]) / a[m - 1] if len(b) >= m else 0.0
    return Ritz(values, q @ v, np.abs(last * v[m - 1]))
