"""What an axis' boundary pair asks of its lines: transform, forced values, padding, modes, flips."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.transforms import dct, dst, inverse_dct, inverse_dst
from .grid import CELL, EVEN, NODE, ODD, PERIODIC, SIDES, UNBOUNDED, Axis, PAIRS


@dataclass(frozen=True)
class LineTransform:
    """The transform of one axis. ``complex_in``: an earlier axis has made the data complex.

    Spectra are stored by mode number. Symmetric pairs of one parity have the same slots (k = 0..m, absent modes are zero), so
    that sine and cosine spectra line up and a derivative needs no shift.
    """

    axis: Axis
    complex_in: bool = False

    @property
    def left_parity(self) -> str:
        return self.axis.right if self.mirrored else self.axis.left

    @property
    def mirrored(self) -> bool:
        """The closed side of a half-open axis is brought to the left."""
        return self.axis.left == UNBOUNDED and self.axis.right != UNBOUNDED

    @cached_property
    def kind(self) -> tuple[str, int]:
        """("dct" | "dst", kind 1-4), or ("dft", 0)."""
        a, node = self.axis, self.axis.layout == NODE
        if a.category >= 3:
            return "dft", 0
        if a.category == 2 or a.left == a.right:
            return ("dct" if self.left_parity == EVEN else "dst"), (1 if node else 2)
        return ("dct" if a.left == EVEN else "dst"), (3 if node else 4)

    @property
    def intervals(self) -> int:
        """Of the transformed line: twice as many if a side is open."""
        return self.axis.n * (2 if self.axis.open else 1)

    @property
    def slots(self) -> int:
        name, kind = self.kind
        if name == "dft":
            return self.intervals if self.complex_in else self.intervals // 2 + 1
        return self.intervals + (1 if kind <= 2 else 0)

    def modes(self) -> np.ndarray:
        """Mode number of each slot; k + 1/2 for mixed pairs, negative beyond the middle of a complex DFT."""
        name, kind = self.kind
        k = np.arange(self.slots, dtype=float)
        if name == "dft" and self.complex_in:
            k[k > self.intervals // 2] -= self.intervals
        return k + (0.5 if kind >= 3 else 0.0)

    def omega(self) -> np.ndarray:
        """Angular frequency of each slot."""
        length = self.axis.h * self.intervals
        return self.modes() * ((2 if self.kind[0] == "dft" else 1) * np.pi / length)

    def forward(self, x: np.ndarray) -> np.ndarray:
        """Lines of ``axis.points`` values to lines of ``slots`` modes; forced values are imposed, open sides padded."""
        a, (name, kind), m = self.axis, self.kind, self.intervals
        if self.mirrored:
            x = x[..., ::-1]
        if name == "dft":
            if a.category == 3:
                x = x[..., : a.n]
            return np.fft.fft(x, m, axis=-1) if self.complex_in or np.iscomplexobj(x) else np.fft.rfft(x, m, axis=-1)
        want = m + (a.layout == NODE)
        if x.shape[-1] < want:
            x = np.concatenate([x, np.zeros((*x.shape[:-1], want - x.shape[-1]))], -1)
        out = np.zeros((*x.shape[:-1], self.slots), x.dtype if np.iscomplexobj(x) else float)
        run = dct if name == "dct" else dst
        if (name, kind) == ("dct", 1):
            out[...] = run(x, 1)
        elif (name, kind) == ("dct", 2):
            out[..., :m] = run(x, 2)
        elif (name, kind) == ("dct", 3):
            out[...] = run(x[..., :m], 3)
        elif (name, kind) == ("dst", 1):
            out[..., 1:m] = run(x[..., 1:m], 1)
        elif (name, kind) == ("dst", 2):
            out[..., 1:] = run(x, 2)
        elif (name, kind) == ("dst", 3):
            out[...] = run(x[..., 1:], 3)
        else:
            out[...] = run(x, 4)
        return out

    def backward(self, y: np.ndarray) -> np.ndarray:
        """The inverse: lines of modes to lines of ``axis.points`` values, duplicated and forced points filled."""
        a, (name, kind), m = self.axis, self.kind, self.intervals
        if name == "dft":
            x = np.fft.ifft(y, axis=-1) if self.complex_in else np.fft.irfft(y, m, axis=-1)
            if a.category == 3 and a.layout == NODE:
                x = np.concatenate([x, x[..., :1]], -1)
            return x[..., : a.points]
        out = np.zeros((*y.shape[:-1], m + (a.layout == NODE)), y.dtype if np.iscomplexobj(y) else float)
        run = inverse_dct if name == "dct" else inverse_dst
        if (name, kind) == ("dct", 1):
            out[...] = run(y, 1)
        elif (name, kind) == ("dct", 2):
            out[...] = run(y[..., :m], 2)
        elif (name, kind) == ("dct", 3):
            out[..., :m] = run(y, 3)
        elif (name, kind) == ("dst", 1):
            out[..., 1:m] = run(y[..., 1:m], 1)
        elif (name, kind) == ("dst", 2):
            out[...] = run(y[..., 1:], 2)
        elif (name, kind) == ("dst", 3):
            out[..., 1:] = run(y, 3)
        else:
            out[...] = run(y, 4)
        out = out[..., : a.points]
        return out[..., ::-1] if self.mirrored else out

    # the kernel's line along an open axis

    @property
    def kernel_points(self) -> int:
        """Offsets at which a kernel is sampled: the whole circle for a DFT, half of it for a real transform."""
        if not self.axis.open:
            return self.slots
        return self.intervals if self.kind[0] == "dft" else self.intervals + 1

    def kernel_offsets(self) -> np.ndarray:
        """Distance, in cells, of each kernel sample: symmetric about the middle of the doubled line."""
        j = np.arange(self.kernel_points)
        return np.minimum(j, self.intervals - j) if self.kind[0] == "dft" else j

    def kernel_forward(self, g: np.ndarray) -> np.ndarray:
        """Always a cosine transform, whatever the data's parity; its slots are the data's. A closed axis has its modes already."""
        if not self.axis.open:
            return g
        if self.kind[0] == "dft":
            return np.fft.fft(g, axis=-1).real if self.complex_in else np.fft.rfft(g, axis=-1).real
        return dct(g, 1)

    # derivatives

    def derivative(self, order: str) -> np.ndarray:
        """Multiplier of each slot for d/dx; real for cosine and sine axes, imaginary for a DFT.

        The next transform of a real axis is that of the flipped parity: sine to cosine has the factor +w, cosine to sine -w.
        """
        w, h = self.omega(), self.axis.h
        if order == "spectral":
            f = w
        else:
            steps = {"fd2": (1.0,), "fd4": (4 / 3, -1 / 6), "fd6": (3 / 2, -3 / 10, 1 / 30)}[order]
            f = sum(c * np.sin((i + 1) * w * h) for i, c in enumerate(steps)) / h
        if self.kind[0] == "dft":
            if self.intervals % 2 == 0:
                f = np.where(np.abs(self.modes()) == self.intervals // 2, 0.0, f)
            return 1j * f
        # a mirrored line runs backwards
        sign = -1.0 if self.mirrored else 1.0
        return sign * (f if self.kind[0] == "dst" else -f)


def transform_table(spark: SparkSession) -> DataFrame:
    """The choice of transform for every layout and boundary pair."""
    rows = []
    for layout in (CELL, NODE):
        for left, right in PAIRS:
            t = LineTransform(Axis(8, left, right, layout))
            name, kind = t.kind
            inverse = {1: 1, 2: 3, 3: 2, 4: 4}.get(kind, 0)
            rows.append((layout, left, right, t.axis.category, name, kind, inverse, t.axis.points, t.intervals, t.slots))
    return spark.createDataFrame(rows, "layout string, `left` string, `right` string, category int, transform string, kind int, inverse_kind int, points int, intervals int, slots int")


def line_transform(axis: Axis, complex_in: bool = False) -> LineTransform:
    return LineTransform(axis, complex_in)


def mode_index(axis: Axis, complex_in: bool = False) -> tuple[np.ndarray, int]:
    """Mode number of each slot, and the slots: sine and cosine spectra of one pair share both."""
    t = LineTransform(axis, complex_in)
    return t.modes(), t.slots


def omega(line: LineTransform, slot: Column) -> Column:
    """Frequency of a slot column, as an expression."""
    name, kind = line.kind
    k = slot.cast("double") + (0.5 if kind >= 3 else 0.0)
    if name == "dft" and line.complex_in:
        k = F.when(k > line.intervals // 2, k - line.intervals).otherwise(k)
    return k * F.lit((2 if name == "dft" else 1) * np.pi / (line.axis.h * line.intervals))


def impose(column: Column, axis: Axis) -> Column:
    """A line column with the values that odd sides force to zero (node-centred lines only)."""
    if axis.layout != NODE:
        return column
    first, last = axis.left == ODD, axis.right == ODD
    return F.transform(column, lambda v, i: F.when(((i == 0) & F.lit(first)) | ((i == axis.n) & F.lit(last)), 0.0).otherwise(v))


def refill(column: Column, axis: Axis) -> Column:
    """Add the duplicate last node of a periodic node-centred line."""
    if axis.category != 3 or axis.layout != NODE:
        return column
    return F.concat(F.slice(column, 1, axis.n), F.slice(column, 1, 1))


def extend(column: Column, axis: Axis) -> Column:
    """Zeros up to the doubled domain of an open axis, on its open side."""
    if not axis.open:
        return column
    extra = LineTransform(axis).intervals + (axis.layout == NODE and axis.category == 2) - axis.points
    zeros = F.array_repeat(F.lit(0.0), extra)
    return F.concat(zeros, column) if LineTransform(axis).mirrored else F.concat(column, zeros)


def restrict(column: Column, axis: Axis) -> Column:
    """The inverse of :func:`extend`."""
    if not axis.open:
        return column
    return F.slice(column, -axis.points, axis.points) if LineTransform(axis).mirrored else F.slice(column, 1, axis.points)


def flip(axis: Axis) -> Axis:
    return axis.flipped()


__all__ = ["LineTransform", "extend", "flip", "impose", "line_transform", "mode_index", "omega", "refill", "restrict", "transform_table", "SIDES", "PERIODIC"]
