"""Noise weights of one stationary interval: first rows of symmetric constant-diagonal blocks and their action."""

from __future__ import annotations

import math

import numpy as np


def inverse_spectrum(f: np.ndarray, sigma2: float = 1.0, fknee: float = 0.1, t_samp: float = 1.0, slope: float = 2.0) -> np.ndarray:
    """1/P with P = sigma2 t_samp (1 + (fknee/f)**slope); zero at f = 0 when there is a knee."""
    fs = np.abs(np.asarray(f, float)) ** slope
    return fs / (sigma2 * t_samp * (fs + fknee**slope)) if fknee > 0 else np.full_like(fs, 1.0 / (sigma2 * t_samp))


def window(lambda_: int, kind: str) -> np.ndarray:
    k = np.arange(lambda_ + 1)
    if kind == "gauss":  # falls off with the lag; a growing one would not leave the weights positive
        return np.exp(-2.0 * (k / max(1, lambda_)) ** 2)
    if kind == "triangle":  # its own spectrum is nowhere negative, so a spectrum that is zero in places stays positive when it is cut to the band
        return 1.0 - k / (lambda_ + 1)
    if kind in ("cut", "none"):
        return np.ones(lambda_ + 1)
    raise ValueError(f"unknown apodisation {kind!r}")


def kernel(fknee: float, lambda_: int | None, sigma2: float = 1.0, grid_n: int = 1024, kind: str = "gauss", slope: float = 2.0, f_cut: float = 0.0) -> np.ndarray:
    """First row, lags 0..lambda_ (None: the whole grid's half, not limited). ``f_cut`` drops all modes below it."""
    f = np.arange(grid_n // 2 + 1) / grid_n
    p = inverse_spectrum(f, sigma2, fknee, 1.0, slope)
    if f_cut > 0:
        p = np.where(f < f_cut, 0.0, p)
    w = np.fft.irfft(p, grid_n)
    if lambda_ is None:
        return w[: grid_n // 2 + 1]
    if lambda_ > grid_n // 2:
        raise ValueError("the band is wider than half the kernel's grid")
    return w[: lambda_ + 1] * window(lambda_, kind)


def white_kernel(sigma2: float = 1.0) -> np.ndarray:
    return np.array([1.0 / sigma2])


def apodized_spectrum(w: np.ndarray, n: int) -> np.ndarray:
    """Eigen-spectrum of the band on a circle of n samples, at f = m/n, m = 0..n/2."""
    row = np.zeros(n)
    row[: len(w)] = w
    row[n - len(w) + 1 :] += w[:0:-1]
    return np.fft.rfft(row).real


def check_positive(w: np.ndarray, n: int | None = None) -> None:
    n = n or max(64, 8 * len(w))
    low = apodized_spectrum(w, n).min()
    if low < -1e-12 * abs(w[0]):
        raise ValueError(f"the kernel is not positive: lowest spectrum value {low:.3g}")


def deflection_frequency(lambda_: int, t_samp: float = 1.0) -> float:
    return 1.0 / (math.pi * lambda_ * t_samp)


def min_lossless_lambda(f_sig: float, t_samp: float = 1.0) -> int:
    return math.ceil(1.0 / (math.pi * f_sig * t_samp))


def white_equivalent_lambda(fknee: float, t_samp: float = 1.0) -> int:
    return math.floor(1.0 / (math.pi * fknee * t_samp))


def fast_length(n: int) -> int:
    """The smallest 2**a 3**b 5**c that is no less than n."""
    best = 1 << max(0, (n - 1).bit_length())
    five = 1
    while five < best:
        three = five
        while three < best:
            two = three
            while two < n:
                two *= 2
            best = min(best, two)
            three *= 3
        five *= 5
    return best


def weight(y: np.ndarray, w: np.ndarray) -> np.ndarray:
    """The block times each row of y (rows are columns of the system) by a zero-padded transform."""
    n = y.shape[-1]
    if len(w) == 1:
        return y * w[0]
    m, v = transform(w, n)
    return np.fft.irfft(np.fft.rfft(y, m) * v, m)[..., :n]


def transform(w: np.ndarray, n: int) -> tuple[int, np.ndarray]:
    """(length, values) of the transform that weights n samples."""
    w = w[:n]
    m = fast_length(n + len(w))
    row = np.zeros(m)
    row[: len(w)] = w
    row[m - len(w) + 1 :] += w[:0:-1]
    return m, np.fft.rfft(row).real


def weight_circulant(y: np.ndarray, fknee: float, sigma2: float = 1.0, slope: float = 2.0, lowest: float = 0.0) -> np.ndarray:
    """Fourier-domain diagonal weighting: the interval is taken as periodic. Its mean is weighted as a mode of ``lowest`` turns."""
    n = y.shape[-1]
    return np.fft.irfft(np.fft.rfft(y) * inverse_spectrum(np.maximum(np.arange(n // 2 + 1), lowest) / n, sigma2, fknee, 1.0, slope), n)


class Stationary:
    """Noise model of banded stationary blocks, one kernel per noise id."""

    def __init__(self, kernels: dict[int, np.ndarray], check: bool = True):
        if check:
            for w in kernels.values():
                check_positive(w)
        self.kernels = kernels
        self.halo = max(len(w) for w in kernels.values()) - 1
        self.known: dict = {}  # transforms by noise id and length, for the blocks of a task

    def __getstate__(self):
        return self.__dict__ | {"known": {}}

    def weight(self, noise_id: int, y: np.ndarray) -> np.ndarray:
        w, n = self.kernels[noise_id], y.shape[-1]
        if len(w) == 1:
            return y * w[0]
        m, v = self.spectrum(noise_id, n)
        modes = np.fft.rfft(y, m)
        modes *= v
        return np.fft.irfft(modes, m)[..., :n]

    def spectrum(self, noise_id: int, n: int) -> tuple[int, np.ndarray]:
        """(length, values) of the transform that weights n samples, kept for the next block."""
        if (noise_id, n) not in self.known:
            if len(self.known) >= 256:
                self.known.clear()
            self.known[noise_id, n] = transform(self.kernels[noise_id], n)
        return self.known[noise_id, n]

    def diag(self, noise_id: int) -> float:
        return float(self.kernels[noise_id][0])


class Circulant:
    """Noise model diagonal in each interval's Fourier modes; intervals are not split."""

    halo = None

    def __init__(self, knees: dict[int, float], sigma2: float = 1.0, lowest: float = 0.0):
        self.knees, self.sigma2, self.lowest = knees, sigma2, lowest

    def weight(self, noise_id, y):
        return weight_circulant(y, self.knees[noise_id], self.sigma2, lowest=self.lowest)

    def diag(self, noise_id):
        return float(inverse_spectrum(np.arange(513) / 1024, self.sigma2, self.knees[noise_id]).mean())


class TemplateMarginalised:
    """W - W T (T' W T)^-1 T' W: a base model with time templates projected out; intervals are not split."""

    halo = None

    def __init__(self, base, templates):
        """``templates(n)`` gives the (q, n) templates of an interval of n samples."""
        self.base, self.templates = base, templates

    def weight(self, noise_id, y):
        t = self.templates(y.shape[-1])
        wt, wy = self.base.weight(noise_id, t), self.base.weight(noise_id, y)
        return wy - (np.linalg.pinv(t @ wt.T) @ (y @ wt.T).T).T @ wt

    def diag(self, noise_id):
        return self.base.diag(noise_id)
