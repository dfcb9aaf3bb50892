"""Analytic test fields with known Laplacians or velocities, on the grid's points (unit cube)."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.special import e2
from ..plans.grid import EVEN, NODE, ODD, PERIODIC, UNBOUNDED, Axis, GridSpec

#: Steepness of the bump; a fixed value of the test cases.
BUMP = 10.0


def bump(t: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """exp(10 (1 - 1 / (1 - t^2))) inside |t| < 1, zero outside; and its second derivative in t."""
    inside = np.abs(t) < 1
    q = np.where(inside, 1 - t * t, 1.0)
    b = np.where(inside, np.exp(BUMP * (1 - 1 / q)), 0.0)
    g1 = -2 * BUMP * t / q**2
    g2 = BUMP * (-2 / q**2 - 8 * t * t / q**3)
    return b, np.where(inside, b * (g2 + g1 * g1), 0.0)


def _line(kind: str, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A factor of the solution and its second derivative in x."""
    if kind == "cos1":
        return np.cos(np.pi * x), -(np.pi**2) * np.cos(np.pi * x)
    if kind == "sin5/2":
        w = 2.5 * np.pi
        return np.sin(w * x), -(w**2) * np.sin(w * x)
    if kind == "sin8":
        w = 8 * np.pi
        return np.sin(w * x), -(w**2) * np.sin(w * x)
    shifts = {"bump": [(1.0, 1.0)], "even_right": [(1.4, 1.0), (2.6, 1.0)], "odd_left": [(0.6, 1.0), (-0.6, -1.0)]}[kind]
    parts = [tuple(s * v for v in bump(2 * x - c)) for c, s in shifts]
    return sum(p[0] for p in parts), 4 * sum(p[1] for p in parts)


CASES = {
    "spectral": (("cos1", "sin5/2", "sin8"), ((EVEN, EVEN), (ODD, EVEN), (PERIODIC, PERIODIC))),
    "unbounded": (("bump", "bump", "bump"), ((UNBOUNDED, UNBOUNDED),) * 3),
    "semi": (("even_right", "bump", "odd_left"), ((UNBOUNDED, EVEN), (UNBOUNDED, UNBOUNDED), (ODD, UNBOUNDED))),
}


def case_grid(case: str, n: int, layout: str = NODE) -> GridSpec:
    return GridSpec.of(*[Axis(n, *pair, layout) for pair in CASES[case][1]])


def scalar_arrays(case: str, spec: GridSpec) -> tuple[np.ndarray, np.ndarray]:
    """(solution, right-hand side) on the whole grid."""
    lines = [_line(kind, a.coordinates()) for kind, a in zip(CASES[case][0], spec.axes)]
    outer = lambda x, y, z: x[:, None, None] * y[:, None] * z
    (x, xx), (y, yy), (z, zz) = lines
    return outer(x, y, z), outer(xx, y, z) + outer(x, yy, z) + outer(x, y, zz)


def tube_grids(n: int, nz: int | None = None, layout: str = NODE) -> list[GridSpec]:
    """Boundaries of the vorticity components of a tube along z: open in x and y; z odd for the in-plane components, even for the third."""
    nz = nz or n
    xy = [Axis(n, UNBOUNDED, UNBOUNDED, layout)] * 2
    return [GridSpec.of(*xy, Axis(nz, p, p, layout, nz / n)) for p in (ODD, ODD, EVEN)]


def tube(x: np.ndarray, y: np.ndarray, profile: str = "gaussian", size: float | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(vorticity, azimuthal velocity / r) of a tube around (1/2, 1/2): a Gaussian of width ``size``, or compact within it."""
    r2 = (x - 0.5) ** 2 + (y - 0.5) ** 2
    if profile == "gaussian":
        s = size or 0.05
        q = r2 / (2 * s * s)
        with np.errstate(divide="ignore", invalid="ignore"):
            turn = np.where(q > 0, -np.expm1(-q) / (2 * np.pi * np.where(q > 0, r2, 1)), 1 / (4 * np.pi * s * s))
        return np.exp(-q) / (2 * np.pi * s * s), turn
    size = size or 0.25
    p = r2 / size**2
    inside = p < 1
    v = np.where(inside, 1 - p, 1.0)
    scale = 1 / (np.pi * size**2 * e2(np.array([1.0]))[0])
    w = np.where(inside, scale * np.exp(-1 / v), 0.0)
    # circulation inside r: the integral of the profile in 1 - p, in terms of the exponential integral
    gone = np.where(inside, v * e2(1 / v), 0.0) / e2(np.array([1.0]))[0]
    with np.errstate(divide="ignore", invalid="ignore"):
        turn = np.where(r2 > 0, (1 - gone) / (2 * np.pi * np.where(r2 > 0, r2, 1)), w / 2)
    return w, turn


def tube_arrays(spec: GridSpec, profile: str = "gaussian", size: float | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(right-hand side f, velocity u), three components each: f is minus the vorticity."""
    x, y, z = (a.coordinates() for a in spec.axes)
    w, turn = tube(x[:, None, None], y[None, :, None], profile, size)
    shape = np.ones((1, 1, len(z)))
    zero = np.zeros((len(x), len(y), len(z)))
    f = np.stack([zero, zero, -w * shape])
    u = np.stack([-(y[None, :, None] - 0.5) * turn * shape, (x[:, None, None] - 0.5) * turn * shape, zero])
    return f, u


def grid_points(spark: SparkSession, spec: GridSpec) -> DataFrame:
    """(ix, iy, iz) of every grid point, from a range."""
    nx, ny, nz = spec.shape
    i = F.col("id")
    return spark.range(nx * ny * nz).select(F.floor(i / (ny * nz)).cast("int").alias("ix"), (F.floor(i / nz) % ny).cast("int").alias("iy"), (i % nz).cast("int").alias("iz"))


def scalar_field(spark: SparkSession, case: str, spec: GridSpec, what: str = "f") -> DataFrame:
    """(ix, iy, iz, v) of the right-hand side ("f") or the solution ("u"), evaluated in the executors."""
    lines = [_line(kind, a.coordinates()) for kind, a in zip(CASES[case][0], spec.axes)]

    def run(frames):
        for p in frames:
            at = (p.ix, p.iy, p.iz)
            v = [a[i] for (a, _), i in zip(lines, at)]
            d = [b[i] for (_, b), i in zip(lines, at)]
            p["v"] = v[0] * v[1] * v[2] if what == "u" else d[0] * v[1] * v[2] + v[0] * d[1] * v[2] + v[0] * v[1] * d[2]
            yield p

    return grid_points(spark, spec).mapInPandas(run, "ix int, iy int, iz int, v double")


def tube_field(spark: SparkSession, spec: GridSpec, what: str = "f", profile: str = "gaussian", size: float | None = None) -> DataFrame:
    """(ix, iy, iz, comp, v) of the three components."""
    x, y, _ = (a.coordinates() for a in spec.axes)

    def run(frames):
        for p in frames:
            w, turn = tube(x[p.ix], y[p.iy], profile, size)
            zero = np.zeros(len(p))
            parts = [zero, zero, -w] if what == "f" else [-(y[p.iy] - 0.5) * turn, (x[p.ix] - 0.5) * turn, zero]
            for c, v in enumerate(parts):
                yield pd.DataFrame({"ix": p.ix, "iy": p.iy, "iz": p.iz, "comp": np.int32(c), "v": v})

    return grid_points(spark, spec).mapInPandas(run, "ix int, iy int, iz int, comp int, v double")
