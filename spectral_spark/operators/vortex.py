"""The curl variant lap(u) = curl(f): derivatives in mode space, flipped parities on the way back."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.boundary import LineTransform
from ..plans.grid import GridSpec
from ..plans.planner import TransformPlan, build
from .exchange import KERNEL, READY, Blocks, is_kernel
from .poisson import Options, multiply, product_of, sweep, workers_of

DERIVATIVES = ("spectral", "fd2", "fd4", "fd6")
#: curl: for each output component two (sign, derivative axis, input component).
CURL = [[(1, 1, 2), (-1, 2, 1)], [(1, 2, 0), (-1, 0, 2)], [(1, 0, 1), (-1, 1, 0)]]


def derivative(line: LineTransform, order: str):
    return line.derivative(order)


def real_factor(line: LineTransform) -> int:
    """+1 where a sine spectrum becomes a cosine spectrum, -1 the other way, 0 for a complex line."""
    return {"dst": 1, "dct": -1, "dft": 0}[line.kind[0]]


def out_specs(specs: list[GridSpec]) -> list[GridSpec]:
    """Boundaries of the solution's components; both terms of each must agree."""
    out = []
    for terms in CURL:
        found = []
        for _, axis, comp in terms:
            axes = list(specs[comp].axes)
            axes[axis] = axes[axis].flipped()
            found.append(GridSpec(tuple(axes)))
        if found[0] != found[1]:
            raise ValueError(f"the terms of a curl component differ in boundaries: {found}")
        out.append(found[0])
    return out


def solve(
    cells: DataFrame,
    specs: list[GridSpec],
    kernel: str = "gauss4",
    derivative: str = "spectral",
    options: Options = Options(),
    origin: str = "cell_mean",
    stored: str | None = None,
) -> DataFrame:
    """(ix, iy, iz, comp, v) of u for ``cells(ix, iy, iz, comp, v)``; ``specs``: the grid of each component of f."""
    w, plans, outs, curl = _prepared(specs, options)
    product = multiply(w, kernel)

    def middle(blocks: Blocks, worker: int) -> Blocks:
        g = {c: blocks.pop(c) for c in (KERNEL, READY) if c in blocks}
        return product(curl(blocks, worker, derivative) | g, worker)

    return sweep(cells, w, plans, middle, outs, options, kernel, origin, stored)


def solve_each(
    cells: DataFrame,
    specs: list[GridSpec],
    kinds: tuple[str, ...] = ("gauss4",),
    derivatives: tuple[str, ...] = DERIVATIVES,
    options: Options = Options(),
    origin: str = "cell_mean",
) -> DataFrame:
    """(kernel, derivative, ix, iy, iz, comp, v) for several kernels and derivatives; the components are transformed once for all."""
    w, plans, outs, curl = _prepared(specs, options)
    product = product_of(w, kinds, 3 * len(derivatives))

    def middle(blocks: Blocks, worker: int) -> Blocks:
        g = {c: blocks.pop(c) for c in list(blocks) if is_kernel(c)}
        each = {3 * i + c: b for i, d in enumerate(derivatives) for c, b in curl(blocks, worker, d).items()}
        return product(each | g, worker)

    back = {c: outs[c % 3] for c in range(3 * len(derivatives) * len(kinds))}
    u = sweep(cells, w, plans, middle, back, options, kinds, origin)
    pick = lambda names, number: F.element_at(F.array(*map(F.lit, names)), number.cast("int") + 1)
    kernel = pick(kinds, F.floor(F.col("comp") / (3 * len(derivatives)))).alias("kernel")
    derivative = pick(derivatives, F.floor(F.col("comp") / 3) % len(derivatives)).alias("derivative")
    return u.select(kernel, derivative, "ix", "iy", "iz", (F.col("comp") % 3).alias("comp"), "v")


def _prepared(specs: list[GridSpec], options: Options):
    """Workers, plans of the components and of the solution, and the curl in mode space."""
    plans = {c: build(s) for c, s in enumerate(specs)}
    outs: dict[int, TransformPlan] = {c: build(s) for c, s in enumerate(out_specs(specs))}
    w = workers_of(specs[0], options)
    orders = {p.order for p in [*plans.values(), *outs.values()]}
    if len(orders) > 1:
        raise ValueError("components must share the order of their axes")

    def curl(blocks: Blocks, worker: int, derivative: str) -> Blocks:
        ranges = w.ranges(worker, 2, done=True)
        out: Blocks = {}
        for c, terms in enumerate(CURL):
            for sign, axis, comp in terms:
                if comp not in blocks:
                    continue
                at = [1, 1, 1]
                d = plans[comp].lines[axis].derivative(derivative)[slice(*ranges[axis])]
                at[axis] = len(d)
                term = sign * d.reshape(at) * blocks[comp]
                out[c] = out[c] + term if c in out else term
        return out

    return w, plans, outs, curl
