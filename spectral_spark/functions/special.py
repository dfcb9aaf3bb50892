"""Special functions by series, continued fractions and fixed quadrature; arrays in, arrays out."""

from __future__ import annotations

from functools import lru_cache
from math import erf as _erf

import numpy as np

EULER = 0.57721566490153286


def erf(x):
    return np.vectorize(_erf, otypes=[float])(x)


@lru_cache
def legendre(n: int) -> tuple[np.ndarray, np.ndarray]:
    return np.polynomial.legendre.leggauss(n)


def ein(z):
    """Entire exponential integral: the integral of (1 - exp(-t)) / t from 0 to z >= 0."""
    z = np.asarray(z, float)
    out = np.zeros_like(z)
    small = z < 2.0
    s, term, k = np.zeros(small.sum()), np.ones(small.sum()), 1
    for k in range(1, 60):
        term = term * (-z[small]) / k
        s = s - term / k
    out[small] = s
    big = z[~small]
    if big.size:
        # exponential integral of order one by its continued fraction, from the bottom
        tail = np.zeros_like(big)
        for j in range(120, 0, -1):
            tail = j / (1 + j / (big + tail))
        out[~small] = np.log(big) + EULER + np.exp(-big) / (big + tail)
    return out


def e2(z):
    """Generalised exponential integral of order two, z >= 0."""
    z = np.asarray(z, float)
    safe = np.where(z > 0, z, 1.0)
    e1 = ein(safe) - np.log(safe) - EULER
    big = safe > 2
    if big.any():
        tail = np.zeros(big.sum())
        for j in range(120, 0, -1):
            tail = j / (1 + j / (safe[big] + tail))
        e1[big] = np.exp(-safe[big]) / (safe[big] + tail)
    return np.where(z > 0, np.exp(-z) - z * e1, 1.0)


def _by_gaps(f, x: np.ndarray) -> np.ndarray:
    """Integral of a smooth, oscillating ``f`` from 0 to each x >= 0: summed over the gaps between the distinct values."""
    grid, back = np.unique(x, return_inverse=True)
    nodes, weights = legendre(16)
    edges = np.concatenate([[0.0], grid])
    width = np.diff(edges)
    parts = np.maximum(1, np.ceil(width / np.pi)).astype(int)
    gap = np.repeat(np.arange(len(grid)), parts)
    step = (width / parts)[gap]
    number = np.arange(len(gap)) - np.repeat(np.cumsum(parts) - parts, parts)
    mid = (edges[:-1][gap] + number * step)[:, None] + (nodes + 1) / 2 * step[:, None]
    pieces = (f(mid) * weights).sum(1) * step / 2
    return np.cumsum(np.bincount(gap, pieces, len(grid)))[back].reshape(x.shape)


def sine_integral(x):
    """Si(x), x >= 0."""
    return _by_gaps(lambda s: np.sinc(s / np.pi), np.asarray(x, float))


def bessel_growth(x):
    """The integral of (1 - J0(s)) / s from 0 to x >= 0."""
    return _by_gaps(lambda s: np.where(s > 1e-4, (1 - bessel_j0(s)) / np.where(s > 0, s, 1), s / 4), np.asarray(x, float))


def bessel_k(order: int, x):
    """Modified Bessel function of the second kind, x > 0, by the trapezoidal rule on its exponential integral."""
    x = np.asarray(x, float)
    t = np.arange(0, 320) * 0.025
    weight = np.full(len(t), 0.025)
    weight[0] /= 2
    flat = x.reshape(-1, 1)
    return (np.exp(-flat * np.cosh(t)) * np.cosh(order * t) @ weight).reshape(x.shape)


def bessel_j0(x):
    """Near the origin by the periodic trapezoidal rule on Bessel's integral, far out by Hankel's expansion."""
    x = np.asarray(x, float)
    out = np.empty_like(x)
    near = x < 30
    theta = (np.arange(60) + 0.5) * np.pi / 120
    out[near] = np.cos(x[near][:, None] * np.sin(theta)).mean(-1)
    y = x[~near]
    p, q, term = np.ones_like(y), np.zeros_like(y), np.ones_like(y)
    for k in range(1, 16):
        term = term * -((2 * k - 1) ** 2) / (8 * k * y)
        if k % 2:
            q += term * (1 if k % 4 == 1 else -1)
        else:
            p += term * (1 if k % 4 == 0 else -1)
    turn = y - np.pi / 4
    out[~near] = np.sqrt(2 / (np.pi * y)) * (p * np.cos(turn) - q * np.sin(turn))
    return out


def bessel_i_scaled(most: int, x: np.ndarray) -> np.ndarray:
    """exp(-x) I_n(x) for n = 0..most and all x > 0, as a table (n, x)."""
    x = np.asarray(x, float)
    out = np.empty((most + 1, len(x)))
    far = x > max(400.0, 4.0 * most * most)
    if far.any():
        y = x[far]
        for n in range(most + 1):
            mu, term, s = 4.0 * n * n, np.ones_like(y), np.ones_like(y)
            for k in range(1, 12):
                term = term * -(mu - (2 * k - 1) ** 2) / (k * 8 * y)
                s += term
            out[n, far] = s / np.sqrt(2 * np.pi * y)
    y = x[~far]
    if y.size:
        # downward recurrence in blocks of comparable arguments
        order = np.argsort(y)
        table = np.empty((most + 1, len(y)))
        for part in np.array_split(order, max(1, len(y) // 64)):
            z = y[part]
            start = int(most + 40 + 6 * np.sqrt(40 * max(z.max(), 1.0)))
            above, here = np.zeros_like(z), np.full_like(z, 1e-280)
            norm, rows = np.zeros_like(z), np.zeros((most + 1, len(z)))
            for n in range(start, 0, -1):
                below = above + 2 * n / z * here
                norm += 2 * here
                if n <= most:
                    rows[n] = here
                above, here = here, below
                huge = np.abs(here) > 1e250
                if huge.any():
                    for a in (above, here, norm):
                        a[huge] *= 1e-250
                    rows[:, huge] *= 1e-250
            rows[0] = here
            table[:, part] = rows / (norm + here)
        out[:, ~far] = table
    return out


def laguerre(n: int, alpha: float, x):
    """Generalised Laguerre polynomial by its recurrence."""
    a, b = np.ones_like(x), 1 + alpha - x
    if n == 0:
        return a
    for k in range(1, n):
        a, b = b, ((2 * k + 1 + alpha - x) * b - (k + alpha) * a) / (k + 1)
    return b
