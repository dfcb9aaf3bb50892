"""SQL registration: line transforms as functions, grids and modes as table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from .transforms import dct, dft_im_column, dft_re_column, dst, lines


def _by_kind(run):
    @pandas_udf("array<double>")
    def apply(series: pd.Series, kind: pd.Series) -> pd.Series:
        out = [None if v is None else np.zeros(0) for v in series]
        for k in kind.dropna().unique():
            part = series.where(kind == k, None)
            for rows, x in lines(part):
                for i, y in zip(rows, run(x, int(k))):
                    out[i] = y
        return pd.Series(out, index=series.index)

    return apply


def register(spark: SparkSession) -> None:
    """``dct(line, kind)``, ``dst(line, kind)``, ``dft_re(line)``, ``dft_im(line)``, ``grid_points(nx, ny, nz)``, ``modes(n, first)``."""
    spark.udf.register("dct", _by_kind(dct))
    spark.udf.register("dst", _by_kind(dst))
    spark.udf.register("dft_re", dft_re_column())
    spark.udf.register("dft_im", dft_im_column())

    @udtf(returnType="ix: int, iy: int, iz: int")
    class GridPoints:
        def eval(self, nx: int, ny: int, nz: int):
            for x in range(nx):
                for y in range(ny):
                    for z in range(nz):
                        yield x, y, z

    @udtf(returnType="k: int, omega: double")
    class Modes:
        def eval(self, n: int, first: int):
            for k in range(n):
                yield k, np.pi * (k + first)

    spark.udtf.register("grid_points", GridPoints)
    spark.udtf.register("modes", Modes)
