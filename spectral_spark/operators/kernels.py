"""Green's kernels: spectra over closed axes, samples over open ones.

With d open axes a kernel is a function of the distance over these and of kappa squared, the sum of the squared frequencies of
the closed axes. Samples depend on the integer distances only, so they are evaluated once per distinct pair.
"""

from __future__ import annotations

from math import comb, factorial

import numpy as np

from ..functions.special import EULER, bessel_growth, bessel_i_scaled, bessel_j0, bessel_k, ein, erf, laguerre, legendre, sine_integral

KERNELS = ("singular", "gauss2", "gauss4", "gauss6", "gauss8", "gauss10", "cutoff", "lattice")
#: ``cutoff`` with the sum of its plane kernel broken off, as in the published runs; of second order there. Not one of the eight.
TRUNCATED = "cutoff_truncated"
#: Terms of that sum, and the argument from which its leading growth replaces it.
TERMS, FAR = 30, 14.0
#: Width of the Gaussian kernels in cells.
SIGMA = 2.0


def kernel_order(kernel: str, spectral: bool = False) -> float:
    """Theoretical order of convergence; infinite where the kernel is exact."""
    if kernel.startswith("gauss"):
        return float(kernel[5:])
    return {"singular": np.inf if spectral else 2.0, "cutoff": np.inf, TRUNCATED: 2.0, "lattice": 2.0}[kernel]


def spectral_kernel(kernel: str, k2: np.ndarray, lattice_k2: np.ndarray, h: float) -> np.ndarray:
    """All axes closed: a closed form per mode. The zero mode, where it exists, is set to zero (solutions of zero mean)."""
    base = lattice_k2 if kernel == "lattice" else k2
    with np.errstate(divide="ignore", invalid="ignore"):
        g = np.where(base > 0, -1.0 / base, 0.0)
    if kernel.startswith("gauss"):
        q = (SIGMA * h) ** 2 / 2 * k2
        g = g * np.exp(-q) * sum(q**j / factorial(j) for j in range(int(kernel[5:]) // 2))
    elif kernel in ("cutoff", TRUNCATED):
        g = np.where(k2 < (np.pi / h) ** 2, g, 0.0)
    return g


def _heat_tail(d: int, tau: float, r2: np.ndarray, kappa2: np.ndarray) -> np.ndarray:
    """-(integral over t from tau of exp(-kappa2 t) (4 pi t)^(-d/2) exp(-r2 / 4t)), kappa2 > 0, in logarithmic time."""
    nodes, weights = legendre(24)
    out = np.empty(len(r2))
    span = np.log(np.maximum(45.0 / (kappa2 * tau), np.e))
    for a in range(0, len(r2), 4096):
        cut = slice(a, a + 4096)
        n = 24
        edges = np.linspace(0, 1, n + 1)
        u = (edges[:-1, None] + (nodes + 1) / 2 / n).ravel()
        s = span[cut, None] * u
        t = tau * np.exp(s)
        f = np.exp(-kappa2[cut, None] * t - r2[cut, None] / (4 * t)) * (4 * np.pi * t) ** (-d / 2) * t
        out[cut] = -(f * np.tile(weights / 2 / n, n)).sum(1) * span[cut]
    return out


def _gauss(order: int, d: int, r: np.ndarray, kappa2: np.ndarray, h: float) -> np.ndarray:
    sigma = SIGMA * h
    tau, rho = sigma**2 / 2, r / sigma
    zero = kappa2 == 0
    g = np.empty(len(r))
    x = r[zero]
    if d == 3:
        with np.errstate(divide="ignore", invalid="ignore"):
            g[zero] = np.where(x > 0, -erf(rho[zero] / np.sqrt(2)) / (4 * np.pi * np.where(x > 0, x, 1)), -np.sqrt(2 / np.pi) / (4 * np.pi * sigma))
    elif d == 2:
        g[zero] = (ein(rho[zero] ** 2 / 2) / 2 + np.log(sigma * np.sqrt(2)) - EULER / 2) / (2 * np.pi)
    else:
        g[zero] = x * erf(rho[zero] / np.sqrt(2)) / 2 + sigma * np.exp(-(rho[zero] ** 2) / 2) / np.sqrt(2 * np.pi)
    if (~zero).any():
        g[~zero] = _heat_tail(d, tau, r[~zero] ** 2, kappa2[~zero])
    heat = (4 * np.pi * tau) ** (-d / 2) * np.exp(-(rho**2) / 2 - kappa2 * tau)
    for j in range(1, order // 2):
        # (-d/dtau)^(j-1) of the heat kernel, times tau^j / j!
        inner = sum(comb(j - 1, i) * (kappa2 * tau) ** (j - 1 - i) * factorial(i) * laguerre(i, d / 2 - 1, rho**2 / 2) for i in range(j))
        g -= tau * heat * inner / factorial(j)
    return g


def _panels(top: np.ndarray, waves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Gauss-Legendre rule on [0, 1], fine enough for so many radians."""
    n = int(4 + np.max(waves, initial=0.0) / 2)
    nodes, weights = legendre(12)
    return ((np.arange(n)[:, None] + (nodes + 1) / 2) / n).ravel(), np.tile(weights / 2 / n, n)


def _broken_off(x: np.ndarray) -> np.ndarray:
    """The integral of (1 - J0(s)) / s from 0 to x: its power series, broken off; far out its logarithm alone."""
    near = np.minimum(x, FAR)
    term, total = np.ones_like(x), np.zeros_like(x)
    for k in range(1, TERMS + 1):
        term = term * (near / 2) ** 2 / (k * k)
        total += (-1) ** (k + 1) * term / (2 * k)
    return np.where(x <= FAR, total, np.log(np.maximum(x, 1e-300) / 2) + EULER)


def _cutoff(d: int, r: np.ndarray, kappa2: np.ndarray, h: float, truncated: bool = False) -> np.ndarray:
    if d == 3:
        safe = np.where(r > 0, r, 1.0)
        return np.where(r > 0, -sine_integral(np.pi * r / h) / (2 * np.pi**2 * safe), -1 / (2 * np.pi * h))
    top2 = (np.pi / h) ** 2 - kappa2
    out = np.zeros(len(r))
    for k2 in np.unique(kappa2):
        at = np.flatnonzero((kappa2 == k2) & (top2 > 0))
        if not len(at):
            continue
        top = np.sqrt(top2[at[0]])
        if d == 2 and k2 == 0 and not truncated:
            out[at] = bessel_growth(top * r[at]) / (2 * np.pi)
            continue
        u, w = _panels(top, top * r[at])
        for part in np.array_split(at, max(1, len(at) // 512)):
            x = r[part, None] * (top * u)
            if d == 2 and k2 == 0 and truncated:
                out[part] = _broken_off(top * r[part]) / (2 * np.pi)
            elif d == 2:
                out[part] = -(bessel_j0(x) * (top * u) / ((top * u) ** 2 + k2) * w).sum(1) * top / (2 * np.pi)
            elif k2 == 0:
                out[part] = (2 * np.sin(x / 2) ** 2 / (top * u) ** 2 * w).sum(1) * top / np.pi
            else:
                out[part] = -(np.cos(x) / ((top * u) ** 2 + k2) * w).sum(1) * top / np.pi
    return out


def _singular(d: int, r: np.ndarray, kappa2: np.ndarray, h: float, origin: str) -> np.ndarray:
    kappa, at0, zero = np.sqrt(kappa2), r == 0, kappa2 == 0
    safe = np.where(at0, 1.0, r)
    if d == 3:
        a = h * (3 / (4 * np.pi)) ** (1 / 3)
        return np.where(at0, -(a**2) / 2 if origin == "published" else -3 / (8 * np.pi * a), -1 / (4 * np.pi * safe))
    if d == 1:
        k = np.where(zero, 1.0, kappa)
        return np.where(zero, r / 2, -np.exp(-k * r) / (2 * k))
    a = h / np.sqrt(np.pi)
    mean0 = (np.pi - 6 + 2 * np.log(np.pi * a * a / 2)) / (8 * np.pi) if origin != "disc" else (np.log(a) - 0.5) / (2 * np.pi)
    g = np.where(at0, mean0, np.log(safe) / (2 * np.pi))
    some = ~zero
    if some.any():
        k = kappa[some]
        mean = -(1 - k * a * bessel_k(1, k * a)) / (np.pi * a * a * k * k)
        g[some] = np.where(at0[some], mean, -bessel_k(0, k * safe[some]) / (2 * np.pi))
    return g


def _lattice(d: int, offsets: list[np.ndarray], kappa2: np.ndarray, h: float) -> np.ndarray:
    """Green's function of the difference Laplacian, from its heat kernel, a product of scaled Bessel functions."""
    q2 = kappa2 * h * h
    if d == 1:
        n = np.abs(offsets[0])
        c = 1 + q2 / 2
        s = np.sqrt(np.maximum(c * c - 1, 0))
        safe = np.where(q2 > 0, s, 1.0)
        return np.where(q2 > 0, -h * np.exp(-n * np.log(c + s)) / (2 * safe), n * h / 2)
    step = 0.08
    u = np.arange(-4.0, 62.0, step)
    t = np.exp(u - np.exp(-u))
    weight = step * t * (1 + np.exp(-u))
    table = bessel_i_scaled(int(max(o.max() for o in offsets)), 2 * t)
    out = np.empty(len(q2))
    for a in range(0, len(out), 2048):
        cut = slice(a, a + 2048)
        f = np.ones((len(q2[cut]), len(t)))
        for o in offsets:
            f *= table[o[cut]]
        if d == 2:
            plain = q2[cut] == 0
            f *= np.exp(-q2[cut, None] * t)
            f[plain] -= table[0] ** 2
        out[cut] = -(f * weight).sum(1) * h ** (2 - d)
    return out


def numbered(key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of non-negative integers and each one's place among them; by counting where they are dense, else by sorting."""
    top = int(key.max()) + 1 if len(key) else 0
    if top > 4 * len(key) + 1024:
        return np.unique(key, return_inverse=True)
    present = np.flatnonzero(np.bincount(key, minlength=top))
    place = np.zeros(top, np.int64)
    place[present] = np.arange(len(present))
    return present, place[key]


def sample(kernel: str, offsets: list[np.ndarray], kappa2: np.ndarray, h: float, origin: str = "cell_mean") -> np.ndarray:
    """Kernel at integer offsets along the open axes (one array per axis) and kappa2, flat arrays of one length.

    A kernel depends on the squared distance and kappa2 alone (``lattice``: on the offsets in any order), so it is evaluated once
    for each distinct pair of these.
    """
    d = len(offsets)
    if len(kappa2) and (kappa2 == kappa2[0]).all():
        levels, level = kappa2[:1], np.zeros(len(kappa2), np.int64)
    else:
        levels, level = np.unique(kappa2, return_inverse=True)
    if kernel == "lattice":
        ordered = np.sort(np.stack(offsets), 0).astype(np.int64)
        size = int(ordered.max(initial=0)) + 1
        key = np.zeros(len(kappa2), np.int64)
        for row in ordered:
            key = key * size + row
    else:
        key = sum(o.astype(np.int64) ** 2 for o in offsets)
    distinct, back = numbered(key * len(levels) + level.ravel())
    k2, at = levels[distinct % max(len(levels), 1)], distinct // max(len(levels), 1)
    if kernel == "lattice":
        rows = [at // size**k % size for k in reversed(range(d))]
        g = _lattice(d, rows, k2, h)
    else:
        r = h * np.sqrt(at)
        if kernel == "singular":
            g = _singular(d, r, k2, h, origin)
        elif kernel in ("cutoff", TRUNCATED):
            g = _cutoff(d, r, k2, h, kernel == TRUNCATED)
        elif kernel in KERNELS:
            g = _gauss(int(kernel[5:]), d, r, k2, h)
        else:
            raise ValueError(f"unknown kernel {kernel}")
    return g[back.ravel()]
