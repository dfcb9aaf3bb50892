"""Order of the axes, their transforms, and the cost of a plan."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np

from .boundary import LineTransform
from .grid import GridSpec


def order_axes(spec: GridSpec) -> tuple[int, int, int]:
    """Symmetric pairs first, then half-open, periodic and open axes: data stays real and small for as long as it can."""
    return tuple(sorted(range(3), key=lambda i: (spec.axes[i].category, i)))


@dataclass(frozen=True)
class TransformPlan:
    spec: GridSpec
    order: tuple[int, int, int]

    @cached_property
    def lines(self) -> dict[int, LineTransform]:
        """By axis. The first DFT in the order reads real data, any later one complex data."""
        out, complex_in = {}, False
        for i in self.order:
            t = LineTransform(self.spec.axes[i])
            if t.kind[0] == "dft":
                t = LineTransform(self.spec.axes[i], complex_in)
                complex_in = True
            out[i] = t
        return out

    def shape_before(self, step: int) -> list[int]:
        """Global shape when the axis of ``step`` is about to be transformed."""
        shape = list(self.spec.shape)
        for i in self.order[:step]:
            shape[i] = self.lines[i].slots
        return shape


def build(spec: GridSpec, order: tuple[int, int, int] | None = None) -> TransformPlan:
    return TransformPlan(spec.validate(), order or order_axes(spec))


def padding_factor(spec: GridSpec) -> float:
    """Mean length of a line's transform volume over the unpadded grid: 14/3 for three open axes."""
    grown, total, real = 1, 0, 0
    for i in order_axes(spec):
        a = spec.axes[i]
        if a.points == 1:
            continue
        real += 1
        grown *= 2 if a.open else 1
        total += grown
    return total / max(real, 1)


def switches(spec: GridSpec, start_axis: int | None = None) -> int:
    """Exchanges of a forward transform: one less if the caller's data is already aligned with the first axis."""
    return 2 if start_axis is not None and start_axis == order_axes(spec)[0] else 3


def volumes(spec: GridSpec) -> list[int]:
    """Values moved by each switch: those of the field after the previous transform, never the padding of the next."""
    plan = build(spec)
    return [int(np.prod(plan.shape_before(s))) for s in range(3)]


def worker_grid(p: int, decomposition: str = "pencil") -> tuple[int, int]:
    """Workers along the two divided axes: (1, p) for slabs, as square as p allows for pencils."""
    if decomposition == "slab":
        return 1, p
    a = int(np.sqrt(p))
    while p % a:
        a -= 1
    return a, p // a


def padded_volume(spec: GridSpec) -> int:
    """Values of the largest array of a solve: the spectrum with every open axis doubled."""
    plan = build(spec)
    return int(np.prod([float(plan.lines[a].slots) for a in range(3)]))


def auto_workers(spec: GridSpec, block_bytes: int = 256 << 20) -> int:
    """The fewest workers whose complex block of the padded field stays within ``block_bytes``."""
    return max(1, -(-16 * padded_volume(spec) // block_bytes))


def auto_decomposition(spec: GridSpec, p: int) -> str:
    """Slabs save one exchange while there are planes for all workers; beyond that pencils."""
    plan = build(spec)
    planes = min(spec.axes[plan.order[2]].points, plan.lines[plan.order[1]].slots)
    return "slab" if p <= planes else "pencil"


def message_model(n: int, p: int, decomposition: str) -> dict[str, float]:
    """Exchanges, peers of each, and values a worker sends in all."""
    if decomposition == "slab":
        return {"switches": 1, "peers": p, "usable_workers": min(p, n), "values_per_worker": n**3 / p}
    return {"switches": 2, "peers": np.sqrt(p), "usable_workers": min(p, n * n), "values_per_worker": 2 * n**3 / p}
