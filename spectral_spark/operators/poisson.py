"""The Poisson solver: forward line transforms, a product with the kernel's spectrum, and the way back."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.boundary import omega as omega_column
from ..plans.grid import GridSpec
from ..plans.planner import TransformPlan, auto_decomposition, auto_workers, build
from ..sources.fields import check_field_schema
from . import kernels
from .exchange import KERNEL, READY, TILE, Blocks, Clock, Workers, cell_columns, generate, is_kernel, onward, own_tiles, start, switch, tile_batch, tiles_as_cells

FIELD = "ix int, iy int, iz int, comp int, v double"
FIELD_ARROW = pa.schema([("ix", pa.int32()), ("iy", pa.int32()), ("iz", pa.int32()), ("comp", pa.int32()), ("v", pa.float64())])
SPECTRUM = "kx int, ky int, kz int, comp int, re double, im double"
SPECTRUM_ARROW = pa.schema([("kx", pa.int32()), ("ky", pa.int32()), ("kz", pa.int32()), ("comp", pa.int32()), ("re", pa.float64()), ("im", pa.float64())])


@dataclass(frozen=True)
class Options:
    """How a solve runs; none of these changes its result.

    A worker's block is one task's: with ``workers`` 0 there are as many as keep it within 256 MB, or more, down to 4 MB, while the
    session has free slots. ``decomposition`` "auto" takes slabs while there are planes for all workers, else pencils. ``batch``:
    tiles per message of the asynchronous switch. ``pending``: most fetches that a receiver has open at a time; Spark fixes it when a
    session starts (:meth:`session_conf`), so a session that has another value is refused. ``clock``: see :func:`clocked`.
    """

    strategy: str = "packed_barrier"
    decomposition: str = "pencil"
    workers: int = 0
    distribution: str = "strided"
    batch: int = 1
    node_size: int = 0
    pending: int | None = None
    clock: object = None

    def session_conf(self) -> dict[str, str]:
        """Settings with which a session must be started for these options."""
        return {} if self.pending is None else {PENDING: str(self.pending)}

    def check(self, spark: SparkSession) -> None:
        for key, value in self.session_conf().items():
            if spark.sparkContext.getConf().get(key, None) != value:
                raise ValueError(f"pending = {self.pending} needs a session that was started with {key}={value}")


#: Fetch requests that a task has in flight.
PENDING = "spark.reducer.maxReqsInFlight"


def clocked(spark: SparkSession) -> object:
    """An accumulator for ``Options.clock``: {(step, on the way back, phase): seconds}."""
    return spark.sparkContext.accumulator({}, Clock())


def on_axis(fn, block: np.ndarray, axis: int) -> np.ndarray:
    return np.moveaxis(fn(np.ascontiguousarray(np.moveaxis(block, axis, -1))), -1, axis)


def kernel_grid(plan: TransformPlan, ranges: list[tuple[int, int]]) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Flat offsets of the open axes, kappa squared and its lattice form, over a box of kernel samples."""
    shape = [b - a for a, b in ranges]
    h = plan.spec.h
    k2, lattice = np.zeros(shape), np.zeros(shape)
    offsets = []
    for a in range(3):
        line, at = plan.lines[a], [1, 1, 1]
        at[a] = shape[a]
        cut = slice(*ranges[a])
        if line.axis.open:
            offsets.append(np.broadcast_to(line.kernel_offsets()[cut].reshape(at), shape).ravel())
        else:
            w = line.omega()[cut].reshape(at)
            k2 = k2 + w**2
            lattice = lattice + (4 / h**2) * np.sin(w * h / 2) ** 2
    return offsets, k2, lattice


def kernel_samples(plan: TransformPlan, kernel: str, ranges: list[tuple[int, int]], origin: str) -> np.ndarray:
    """Kernel on a box: modes along closed axes, distances along open ones."""
    offsets, k2, lattice = kernel_grid(plan, ranges)
    if not offsets:
        return kernels.spectral_kernel(kernel, k2, lattice, plan.spec.h)
    kappa2 = (lattice if kernel == "lattice" else k2).ravel()
    return kernels.sample(kernel, offsets, kappa2, plan.spec.h, origin).reshape(k2.shape) * plan.spec.h ** len(offsets)


def forward_step(w: Workers, step: int, plans: dict[int, TransformPlan]):
    """Work of a forward line pass: each component by its own plan, a kernel by cosine transforms."""
    axis = w.plan.order[step]

    def work(blocks: Blocks, worker: int) -> Blocks:
        line = lambda c: w.plan.lines[axis].kernel_forward if is_kernel(c) else plans[c].lines[axis].forward
        return {c: b if c == READY else on_axis(line(c), b, axis) for c, b in blocks.items()}

    return work


def backward_step(w: Workers, step: int, plans: dict[int, TransformPlan]):
    axis = w.plan.order[step]

    def work(blocks: Blocks, worker: int) -> Blocks:
        return {c: on_axis(plans[c].lines[axis].backward, b, axis) for c, b in blocks.items()}

    return work


def _chain(*works):
    def work(blocks: Blocks, worker: int) -> Blocks:
        for f in works:
            blocks = f(blocks, worker)
        return blocks

    return work


def _field_rows(w: Workers):
    def finish(blocks: Blocks, worker: int):
        for comp, at, v in cell_columns(blocks, w, worker, 0):
            yield pa.RecordBatch.from_arrays([*[pa.array(x.astype(np.int32)) for x in at], pa.array(np.full(len(v), comp, np.int32)), pa.array(np.ascontiguousarray(v.real))], schema=FIELD_ARROW)

    return finish


def _spectrum_rows(w: Workers):
    def finish(blocks: Blocks, worker: int):
        for comp, at, v in cell_columns(blocks, w, worker, 2):
            im = pa.array(np.ascontiguousarray(v.imag)) if np.iscomplexobj(v) else pa.array(np.zeros(len(v)))
            names = [*[pa.array(x.astype(np.int32)) for x in at], pa.array(np.full(len(v), comp, np.int32))]
            yield pa.RecordBatch.from_arrays([*names, pa.array(np.ascontiguousarray(v.real)), im], schema=SPECTRUM_ARROW)

    return finish


def checked_cells(cells: DataFrame, spec: GridSpec) -> DataFrame:
    """``cells`` with a component, an error for any that lies outside the grid or has no index, and zero for a null value.

    A value that is not finite spoils its component, as it does in any Fourier method; it is not searched for.
    """
    cells = check_field_schema(cells)
    if "comp" not in cells.columns:
        cells = cells.withColumn("comp", F.lit(0))
    names = ["ix", "iy", "iz", "comp"]
    inside = F.lit(True)
    for name, n in zip(names, spec.shape):
        inside = inside & F.col(name).isNotNull() & F.col(name).between(0, n - 1)
    inside = inside & F.col("comp").isNotNull() & (F.col("comp") >= 0)
    where = F.concat_ws(", ", *[F.coalesce(F.col(c).cast("string"), F.lit("null")) for c in names])
    error = F.raise_error(F.concat(F.lit("cell outside the grid (ix, iy, iz, comp): "), where))
    return cells.select(F.when(inside, F.col("ix")).otherwise(error.cast("int")).alias("ix"), "iy", "iz", "comp", F.coalesce("v", F.lit(0.0)).alias("v"))


def _field_tiles(w: Workers):
    def finish(blocks: Blocks, worker: int):
        origin = [a for a, _ in w.ranges(worker, 0)]
        yield tile_batch([(worker, worker, 0, c, origin, list(b.shape), np.ascontiguousarray(b.real), None) for c, b in blocks.items()])

    return finish


def sweep(
    cells: DataFrame | None,
    w: Workers,
    plans: dict[int, TransformPlan],
    middle,
    out_plans: dict[int, TransformPlan] | None,
    options: Options,
    kernel: str | list[str] | None = None,
    origin: str = "cell_mean",
    stored: str | None = None,
    make=None,
    spark: SparkSession | None = None,
) -> DataFrame:
    """The whole path: lines of the first, second and third axis, ``middle`` in mode space, and, if ``out_plans``, back.

    A kernel with open axes is sampled by the workers and carried through the same switches as a component of its own, or its
    ``stored`` spectrum joins the field at the last switch. Instead of ``cells``, ``make(ranges)`` can give each worker its block
    of the first axis' lines; the result is then tiles of the same owners, and two switches are made each way.
    """
    spark = spark or cells.sparkSession
    options.check(spark)
    s, b = options.strategy, options.batch
    steps = [forward_step(w, k, plans) for k in range(3)]
    fused = w.local(0, 1)  # slabs: the first two axes are transformed where they are
    first = _chain(steps[0], steps[1]) if fused else steps[0]
    to = 2 if fused else 1
    if make is None:
        sent = start(checked_cells(cells, w.plan.spec), w, first, s, b, to)
    else:
        sent = generate(spark, w, lambda worker: first({0: make(w.ranges(worker, 0))}, worker), s, b, to)
    finish, schema = (_field_rows(w), FIELD) if make is None else (_field_tiles(w), TILE)
    if kernel is not None and w.plan.spec.open_axes and stored is None:
        sent = sent.unionByName(generate(spark, w, _kernel_maker(w, kernel, origin, first), s, b, to))
    if not fused:
        sent = onward(sent, w, 1, 2, steps[1], s, b)
    if stored is not None:
        ready = spark.read.schema(TILE).parquet(stored)
        sent = sent.unionByName(tiles_as_cells(ready) if s == "unpacked_direct" else ready)
    if out_plans is None:
        return switch(sent, w, 2, _chain(steps[2], middle), _spectrum_rows(w), SPECTRUM, s)
    back = [backward_step(w, k, out_plans) for k in range(3)]
    if fused:
        sent = onward(sent, w, 2, 1, _chain(steps[2], middle, back[2]), s, b)
        return switch(sent, w, 1, _chain(back[1], back[0]), finish, schema, s, True)
    sent = onward(sent, w, 2, 1, _chain(steps[2], middle, back[2]), s, b)
    sent = onward(sent, w, 1, 0, back[1], s, b, True)
    return switch(sent, w, 0, back[0], finish, schema, s, True)


def _kernel_maker(w: Workers, kernel: str | list[str], origin: str, first):
    kinds = [kernel] if isinstance(kernel, str) else kernel

    def make(worker: int) -> Blocks:
        return first({KERNEL - i: kernel_samples(w.plan, k, w.ranges(worker, 0, True), origin) for i, k in enumerate(kinds)}, worker)

    return make


def store_spectrum(spark: SparkSession, spec: GridSpec, kernel: str, folder: str, options: Options = Options(), origin: str = "cell_mean") -> str:
    """Write a kernel's spectrum once, as its owners' tiles, and return its path: solves of the same grid and options read it and
    save the kernel's line passes and switches. The path names all that the tiles depend on; an existing one is used again."""
    w = workers_of(spec, options)
    path = f"{folder.rstrip('/')}/{spec.key()}-{kernel}-{origin}-{w.decomposition}-{w.p}-{w.distribution}"
    conf, p = spark.sparkContext._jsc.hadoopConfiguration(), spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    if p.getFileSystem(conf).exists(p):
        return path
    steps = [forward_step(w, k, {}) for k in range(3)]
    fused = w.local(0, 1)
    first, to = (_chain(steps[0], steps[1]), 2) if fused else (steps[0], 1)
    sent = generate(spark, w, _kernel_maker(w, kernel, origin, first), "packed_barrier", 1, to)
    if not fused:
        sent = onward(sent, w, 1, 2, steps[1], "packed_barrier", 1)

    def keep(blocks: Blocks, worker: int):
        yield own_tiles({READY: blocks[KERNEL]}, w, worker)

    switch(sent, w, 2, steps[2], keep, TILE, "packed_barrier").write.mode("overwrite").parquet(path)
    return path


def multiply(w: Workers, kernel: str):
    """Product with the kernel's spectrum; the closed form where all axes are closed."""

    def work(blocks: Blocks, worker: int) -> Blocks:
        g = blocks.pop(KERNEL, None)
        g = blocks.pop(READY, g)
        if g is None:
            if w.plan.spec.open_axes:
                # no cell of this worker's share has a kernel: nothing was sent
                return {}
            g = kernel_samples(w.plan, kernel, w.ranges(worker, 2, done=True), "cell_mean")
        return {c: b * g for c, b in blocks.items()}

    return work


def product_of(w: Workers, kinds: list[str], comps: int):
    """Products with several kernels: component c times kernel i becomes component i * comps + c."""

    def work(blocks: Blocks, worker: int) -> Blocks:
        g = [blocks.pop(KERNEL - i, None) for i in range(len(kinds))]
        if w.plan.spec.open_axes and any(x is None for x in g):
            return {}
        if not w.plan.spec.open_axes:
            g = [kernel_samples(w.plan, k, w.ranges(worker, 2, done=True), "cell_mean") for k in kinds]
        return {i * comps + c: b * x for i, x in enumerate(g) for c, b in blocks.items()}

    return work


def workers_of(spec: GridSpec, options: Options) -> Workers:
    p = options.workers
    if not p:
        session = SparkSession.getActiveSession()
        slots = session.sparkContext.defaultParallelism if session else 1
        p = max(auto_workers(spec), min(slots, auto_workers(spec, 4 << 20)))
    kind = auto_decomposition(spec, p) if options.decomposition == "auto" else options.decomposition
    return Workers(build(spec), p, kind, options.distribution, options.node_size, options.clock)


def solve(cells: DataFrame, spec: GridSpec, kernel: str = "gauss4", options: Options = Options(), origin: str = "cell_mean", stored: str | None = None) -> DataFrame:
    """(ix, iy, iz, comp, v) of the solution of lap(u) = f for f in ``cells`` (ix, iy, iz, v[, comp]).

    Missing cells and null values are zero, cells that are given twice add up, and a table without rows has no solution rows. A cell
    outside the grid or without an index is an error that names it. If every boundary is periodic or even the
    solution is the one of zero mean, of f less its mean.
    """
    w = workers_of(spec, options)
    plans = _Same(w.plan)
    return sweep(cells, w, plans, multiply(w, kernel), plans, options, kernel, origin, stored)


def solve_each(cells: DataFrame, spec: GridSpec, kinds: list[str], options: Options = Options(), origin: str = "cell_mean") -> DataFrame:
    """(kernel, ix, iy, iz, v) of the solutions by several kernels: the right-hand side, of one component, is transformed once."""
    w = workers_of(spec, options)
    plans = _Same(w.plan)
    u = sweep(cells, w, plans, product_of(w, kinds, 1), plans, options, kinds, origin)
    return u.select(F.element_at(F.array(*map(F.lit, kinds)), F.col("comp") + 1).alias("kernel"), "ix", "iy", "iz", "v")


def solve_aligned(spark: SparkSession, spec: GridSpec, make, kernel: str | None = "gauss4", options: Options = Options(), origin: str = "cell_mean", stored: str | None = None) -> DataFrame:
    """A solve of data that already lies along the first axis: ``make(ranges)`` returns the right-hand side on a box of points.

    The result is a tile per worker (offset, shape, float64 bytes) in the same layout, so no value is ever a row of its own. Without a
    kernel it is the forward and backward transform alone.
    """
    w = workers_of(spec, options)
    same = _Same(w.plan)
    middle = multiply(w, kernel) if kernel else lambda blocks, worker: blocks
    return sweep(None, w, same, middle, same, options, kernel, origin, stored, make, spark)


class _Same(dict):
    """One plan for every component."""

    def __init__(self, plan):
        super().__init__()
        self.plan = plan

    def __missing__(self, key):
        return self.plan

    def __reduce__(self):
        return _Same, (self.plan,)


def forward(cells: DataFrame, spec: GridSpec, options: Options = Options()) -> DataFrame:
    """Spectrum (kx, ky, kz, comp, re, im) by slot numbers."""
    w = workers_of(spec, options)
    return sweep(cells, w, _Same(w.plan), lambda blocks, worker: blocks, None, options)


def round_trip(cells: DataFrame, spec: GridSpec, options: Options = Options()) -> DataFrame:
    w = workers_of(spec, options)
    same = _Same(w.plan)
    return sweep(cells, w, same, lambda blocks, worker: blocks, same, options)


def spectrum(spark: SparkSession, spec: GridSpec, kernel: str, options: Options = Options(), origin: str = "cell_mean") -> DataFrame:
    """The kernel's spectrum (kx, ky, kz, re), distributed as the field's: to be written once and used for many solves."""
    w = workers_of(spec, options)
    plan = w.plan
    names = ["kx", "ky", "kz"]
    if not spec.open_axes:
        table = spark.range(int(np.prod([plan.lines[a].slots for a in range(3)])))
        ny, nz = plan.lines[1].slots, plan.lines[2].slots
        at = [F.floor(F.col("id") / (ny * nz)), F.floor(F.col("id") / nz) % ny, F.col("id") % nz]
        return closed_form(table.select(*[a.cast("int").alias(n) for a, n in zip(at, names)]), spec, kernel)
    seed = spark.createDataFrame([(0, 0, 0, 0.0)], "ix int, iy int, iz int, v double")

    def only_kernel(blocks: Blocks, worker: int) -> Blocks:
        return {0: blocks[KERNEL]} if KERNEL in blocks else {}

    return sweep(seed, w, _Same(plan), only_kernel, None, options, kernel, origin).select(*names, "re")


def closed_form(modes: DataFrame, spec: GridSpec, kernel: str) -> DataFrame:
    """``modes(kx, ky, kz)`` with the kernel ``re`` as a column expression: no table and no join (closed axes only)."""
    plan, h = build(spec), spec.h
    w = [omega_column(plan.lines[a], F.col(c)) for a, c in enumerate(("kx", "ky", "kz"))]
    k2 = sum((x * x for x in w[1:]), w[0] * w[0])
    if kernel == "lattice":
        base = sum((F.pow(F.sin(x * (h / 2)), 2) * (4 / h**2) for x in w), F.lit(0.0))
    else:
        base = k2
    g = F.when(base > 0, -1.0 / base).otherwise(0.0)
    if kernel.startswith("gauss"):
        q = k2 * ((kernels.SIGMA * h) ** 2 / 2)
        total, term = F.lit(1.0), F.lit(1.0)
        for j in range(1, int(kernel[5:]) // 2):
            term = term * q / j
            total = total + term
        g = g * F.exp(-q) * total
    elif kernel == "cutoff":
        g = F.when(k2 < (np.pi / h) ** 2, g).otherwise(0.0)
    return modes.withColumn("re", g)
