"""Real and complex line transforms over batches of lines (NumPy, last axis), and as Arrow-vectorised columns.

Forward sums are not normalised; those of the cosine and sine kinds carry a factor 2 on inner terms. Every cosine and sine kind
is one complex DFT of the line, shifted by half a mode or half a cell where its kind needs that.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf


def _spectrum(x: np.ndarray, n: int, half_mode: bool) -> np.ndarray:
    """sum_j x_j exp(-2 pi i (k + half) j / n) for k = 0..n-1, x zero-padded to n."""
    if half_mode:
        x = x * np.exp(-1j * np.pi * np.arange(x.shape[-1]) / n)
    return np.fft.fft(x, n, axis=-1)


def _parts(x, real):
    return real(x.real) + 1j * real(x.imag) if np.iscomplexobj(x) else real(x)


def dct(x: np.ndarray, kind: int) -> np.ndarray:
    """Kinds 1 (n + 1 values in and out) and 2, 3, 4 (n values) for n intervals."""

    def real(x):
        x = np.asarray(x, float)
        n = x.shape[-1] - (kind == 1)
        if kind == 1:
            if n == 0:
                return x.copy()
            return np.fft.rfft(np.concatenate([x, x[..., -2:0:-1]], -1), axis=-1).real
        k = np.arange(n)
        if kind == 2:
            turn = np.exp(-1j * np.pi * k / (2 * n))
            return 2 * (turn * _spectrum(x, 2 * n, False)[..., :n]).real
        if kind == 3:
            x = np.concatenate([x[..., :1] / 2, x[..., 1:]], -1)
            return 2 * _spectrum(x, 2 * n, True)[..., :n].real
        turn = np.exp(-1j * np.pi * (k + 0.5) / (2 * n))
        return 2 * (turn * _spectrum(x, 2 * n, True)[..., :n]).real

    return _parts(x, real)


def dst(x: np.ndarray, kind: int) -> np.ndarray:
    """Kind 1: points and modes 1..n-1; 2: modes 1..n; 3: points 1..n; 4: n values."""

    def real(x):
        x = np.asarray(x, float)
        n = x.shape[-1] + (kind == 1)
        if kind == 1:
            if n == 1:
                return x.copy()
            zero = np.zeros((*x.shape[:-1], 1))
            return -np.fft.rfft(np.concatenate([zero, x, zero, -x[..., ::-1]], -1), axis=-1).imag[..., 1:n]
        k = np.arange(n)
        if kind == 2:
            turn = np.exp(-1j * np.pi * (k + 1) / (2 * n))
            return -2 * (turn * np.fft.fft(x, 2 * n, axis=-1)[..., 1 : n + 1]).imag
        if kind == 3:
            x = np.concatenate([np.zeros((*x.shape[:-1], 1)), x[..., :-1], x[..., -1:] / 2], -1)
            return -2 * _spectrum(x, 2 * n, True)[..., :n].imag
        turn = np.exp(-1j * np.pi * (k + 0.5) / (2 * n))
        return -2 * (turn * _spectrum(x, 2 * n, True)[..., :n]).imag

    return _parts(x, real)


#: Kind of the inverse, which divides by twice the number of intervals.
INVERSE_KIND = {1: 1, 2: 3, 3: 2, 4: 4}


def inverse_dct(x: np.ndarray, kind: int) -> np.ndarray:
    return dct(x, INVERSE_KIND[kind]) / (2 * (x.shape[-1] - (kind == 1)))


def inverse_dst(x: np.ndarray, kind: int) -> np.ndarray:
    return dst(x, INVERSE_KIND[kind]) / (2 * (x.shape[-1] + (kind == 1)))


def lines(series: pd.Series) -> list[tuple[np.ndarray, np.ndarray]]:
    """Rows of an array column grouped by length: (row numbers, one line a row). Null rows are left out."""
    size = series.map(lambda v: -1 if v is None else len(v)).to_numpy()
    return [(np.flatnonzero(size == n), np.stack(series.to_numpy()[size == n]).astype(float)) for n in np.unique(size) if n > 0]


def _column(name: str, run):
    """An Arrow-vectorised column function from array<double> to array<double>; null and empty lines stay as they are."""

    @pandas_udf("array<double>")
    def apply(series: pd.Series) -> pd.Series:
        out = [None if v is None else np.zeros(0) for v in series]
        for rows, x in lines(series):
            for i, y in zip(rows, run(x)):
                out[i] = y
        return pd.Series(out, index=series.index)

    apply.__name__ = name
    return apply


def dct_column(kind: int, inverse: bool = False):
    return _column(f"dct{kind}", lambda x: inverse_dct(x, kind) if inverse else dct(x, kind))


def dst_column(kind: int, inverse: bool = False):
    return _column(f"dst{kind}", lambda x: inverse_dst(x, kind) if inverse else dst(x, kind))


def dft_re_column():
    return _column("dft_re", lambda x: np.fft.rfft(x, axis=-1).real)


def dft_im_column():
    return _column("dft_im", lambda x: np.fft.rfft(x, axis=-1).imag)


def dft_r2c_column():
    """Half spectrum (re, im) of real lines."""

    @pandas_udf("struct<re:array<double>,im:array<double>>")
    def apply(series: pd.Series) -> pd.DataFrame:
        re, im = [None] * len(series), [None] * len(series)
        for rows, x in lines(series):
            for i, v in zip(rows, np.fft.rfft(x, axis=-1)):
                re[i], im[i] = v.real, v.imag
        return pd.DataFrame({"re": re, "im": im})

    return apply


def dft_c2r_column(n: int):
    """Real lines of ``n`` points from half spectra (two columns)."""

    @pandas_udf("array<double>")
    def apply(re: pd.Series, im: pd.Series) -> pd.Series:
        return pd.Series([None if a is None else np.fft.irfft(np.asarray(a) + 1j * np.asarray(b), n) for a, b in zip(re, im)], index=re.index)

    return apply


def dft_c2c_column(sign: int = -1):
    """Complex lines: sign -1 forward, +1 inverse with division by the length."""

    @pandas_udf("struct<re:array<double>,im:array<double>>")
    def apply(re: pd.Series, im: pd.Series) -> pd.DataFrame:
        out = [None if a is None else (np.fft.fft if sign < 0 else np.fft.ifft)(np.asarray(a) + 1j * np.asarray(b)) for a, b in zip(re, im)]
        return pd.DataFrame({"re": [None if y is None else y.real for y in out], "im": [None if y is None else y.imag for y in out]})

    return apply


def as_doubles(column):
    return F.transform(column, lambda v: v.cast("double"))
