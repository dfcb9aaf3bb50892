"""Plain ways to the same results: whole-array transforms, direct sums, per-axis cell shuffles."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.transforms import dft_c2c_column
from ..plans.grid import GridSpec
from ..plans.planner import build
from .poisson import kernel_samples, on_axis


def monolithic_solve(f: np.ndarray, spec: GridSpec, kernel: str, origin: str = "cell_mean") -> np.ndarray:
    """One process, one array."""
    plan = build(spec)
    y = f
    for a in plan.order:
        y = on_axis(plan.lines[a].forward, y, a)
    y = y * monolithic_spectrum(spec, kernel, origin)
    for a in reversed(plan.order):
        y = on_axis(plan.lines[a].backward, y, a)
    return y


def monolithic_spectrum(spec: GridSpec, kernel: str, origin: str = "cell_mean") -> np.ndarray:
    plan = build(spec)
    g = kernel_samples(plan, kernel, [(0, plan.lines[a].kernel_points) for a in range(3)], origin)
    for a in plan.order:
        g = on_axis(plan.lines[a].kernel_forward, g, a)
    return g


def monolithic_curl_solve(f: np.ndarray, specs: list[GridSpec], kernel: str, derivative: str = "spectral", origin: str = "cell_mean") -> np.ndarray:
    from .vortex import CURL, out_specs

    plans, outs = [build(s) for s in specs], [build(s) for s in out_specs(specs)]
    y = []
    for plan, x in zip(plans, f):
        for a in plan.order:
            x = on_axis(plan.lines[a].forward, x, a)
        y.append(x)
    g = monolithic_spectrum(specs[0], kernel, origin)
    u = []
    for c, terms in enumerate(CURL):
        total = 0
        for sign, axis, comp in terms:
            at = [1, 1, 1]
            d = plans[comp].lines[axis].derivative(derivative)
            at[axis] = len(d)
            total = total + sign * d.reshape(at) * y[comp]
        total = total * g
        for a in reversed(outs[c].order):
            total = on_axis(outs[c].lines[a].backward, total, a)
        u.append(total)
    return np.stack(u)


def monolithic_fft(spark: SparkSession, cells: DataFrame, n: int) -> DataFrame:
    """The whole cube in one task: forward and backward periodic transform. Its memory is the grid's."""

    def run(table):
        import pyarrow as pa

        cube = np.zeros((n, n, n))
        at = tuple(table.column(c).to_numpy() for c in ("ix", "iy", "iz"))
        np.add.at(cube, at, table.column("v").to_numpy())
        back = np.fft.irfftn(np.fft.rfftn(cube), cube.shape, axes=(0, 1, 2))
        i = np.indices(cube.shape).reshape(3, -1).astype(np.int32)
        return pa.table({"ix": i[0], "iy": i[1], "iz": i[2], "v": back.ravel()})

    return cells.select("ix", "iy", "iz", "v").groupBy(F.lit(0).alias("one")).applyInArrow(run, "ix int, iy int, iz int, v double")


def cell_shuffle_fft(cells: DataFrame, n: int, inverse: bool = False) -> DataFrame:
    """DataFrame operators alone: per axis collect the line, transform, explode. (ix, iy, iz, re, im) in and out."""
    out = cells
    for axis in ("ix", "iy", "iz"):
        others = [c for c in ("ix", "iy", "iz") if c != axis]
        lines = out.groupBy(*others).agg(F.array_sort(F.collect_list(F.struct(axis, "re", "im"))).alias("line"))
        lines = lines.withColumn("y", dft_c2c_column(1 if inverse else -1)(F.col("line.re"), F.col("line.im")))
        out = lines.select(*others, F.posexplode(F.arrays_zip(F.col("y.re").alias("re"), F.col("y.im").alias("im"))).alias(axis, "p"))
        # zipped arrays name their parts by number or by column
        re, im = out.schema["p"].dataType.names
        out = out.select(*[F.col(c).cast("int").alias(c) for c in ("ix", "iy", "iz")], F.col("p")[re].alias("re"), F.col("p")[im].alias("im"))
    return out


def direct_sum(cells: DataFrame, kernel: DataFrame) -> DataFrame:
    """u_i = sum_j G(|i - j|) f_j for (ix, iy, iz, v) and ``kernel(n2, g)``: every pair of non-empty cells and points; for tests."""
    a = cells.select(*[F.col(c).alias(f"a{c}") for c in ("ix", "iy", "iz")])
    b = cells.where("v <> 0")
    d2 = sum((F.pow(F.col(f"a{c}") - F.col(c), 2) for c in ("iy", "iz")), F.pow(F.col("aix") - F.col("ix"), 2)).cast("long")
    pairs = a.crossJoin(b).withColumn("n2", d2)
    return pairs.join(F.broadcast(kernel), "n2").groupBy(F.col("aix").alias("ix"), F.col("aiy").alias("iy"), F.col("aiz").alias("iz")).agg(F.sum(F.col("g") * F.col("v")).alias("v"))
