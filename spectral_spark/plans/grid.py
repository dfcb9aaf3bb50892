"""Axes and grids: layout, boundary pair, size and extent of every direction."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, replace

import numpy as np

EVEN, ODD, PERIODIC, UNBOUNDED = "even", "odd", "periodic", "unbounded"
CELL, NODE = "cell", "node"
SIDES = (EVEN, ODD, UNBOUNDED)

#: The ten boundary pairs of an axis.
PAIRS = [
    (EVEN, EVEN), (ODD, ODD), (ODD, EVEN), (EVEN, ODD), (PERIODIC, PERIODIC), (UNBOUNDED, UNBOUNDED),
    (EVEN, UNBOUNDED), (ODD, UNBOUNDED), (UNBOUNDED, EVEN), (UNBOUNDED, ODD),
]


@dataclass(frozen=True)
class Axis:
    """``n`` intervals over ``length``; cell-centred data has n points, node-centred data n + 1."""

    n: int
    left: str = PERIODIC
    right: str = PERIODIC
    layout: str = NODE
    length: float = 1.0

    def __post_init__(self):
        if self.n < 1 or self.length <= 0:
            raise ValueError("an axis needs an interval and an extent")
        if (self.left, self.right) not in PAIRS or self.layout not in (CELL, NODE):
            raise ValueError(f"unknown boundary or layout: {self}")

    @property
    def h(self) -> float:
        return self.length / self.n

    @property
    def points(self) -> int:
        return self.n + (self.layout == NODE)

    @property
    def category(self) -> int:
        """1 symmetric pair, 2 semi-unbounded, 3 periodic, 4 unbounded: the order in which axes are transformed."""
        if self.left == PERIODIC:
            return 3
        open_sides = (self.left == UNBOUNDED) + (self.right == UNBOUNDED)
        return (1, 2, 4)[open_sides]

    @property
    def open(self) -> bool:
        return self.category in (2, 4)

    def coordinates(self) -> np.ndarray:
        return (np.arange(self.points) + (0.5 if self.layout == CELL else 0.0)) * self.h

    def flipped(self) -> Axis:
        """Parity of every closed side changed, as a derivative along the axis does."""
        turn = {EVEN: ODD, ODD: EVEN}
        return replace(self, left=turn.get(self.left, self.left), right=turn.get(self.right, self.right))


@dataclass(frozen=True)
class GridSpec:
    """Three axes; a missing direction is a periodic axis of one cell. Real directions share one spacing."""

    axes: tuple[Axis, Axis, Axis]

    @staticmethod
    def of(*axes: Axis) -> GridSpec:
        blank = Axis(1, layout=CELL)
        return GridSpec((*axes, *[blank] * (3 - len(axes)))).validate()

    def validate(self) -> GridSpec:
        if len(self.axes) != 3:
            raise ValueError("a grid has three axes")
        real = [a for a in self.axes if a.points > 1]
        if real and any(abs(a.h / real[0].h - 1) > 1e-12 for a in real):
            raise ValueError("all axes need the same spacing")
        return self

    @property
    def h(self) -> float:
        return next((a.h for a in self.axes if a.points > 1), self.axes[0].h)

    @property
    def shape(self) -> tuple[int, int, int]:
        return tuple(a.points for a in self.axes)

    @property
    def open_axes(self) -> list[int]:
        return [i for i, a in enumerate(self.axes) if a.open]

    def key(self) -> str:
        return hashlib.sha256(repr(self).encode()).hexdigest()[:16]

    def rows(self) -> list[tuple]:
        return [(name, a.n, a.length, a.layout, a.left, a.right) for name, a in zip("xyz", self.axes)]


AXIS_SCHEMA = "name string, n int, length double, layout string, left string, right string"
