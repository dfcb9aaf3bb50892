"""Switches: moving a field from lines of one axis to lines of another, in three ways.

A worker holds whole lines of the active axis and a range of the other two. At a switch it cuts its block into tiles, one for
each receiver, which pastes them into a zeroed block. Third-axis ranges do not change at a switch, so a worker
exchanges with the peers of its row or column of the worker grid only.

- ``packed_barrier``: all tiles are packed; a receiver pastes when all of its tiles have arrived.
- ``batched_async``: tiles leave in batches of bounded size and are pasted as they come, in any order (no sort).
- ``unpacked_direct``: cells are sent as rows, without packing; the receiver alone orders them.

All three place a worker by its number, so that each is one task. Zeros of padded axes are made by the receiver and cut off before
sending back, so they are never moved. A complex tile is sent as it lies in memory (``re`` holds both parts, ``im`` is empty).
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import AccumulatorParam
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.distribution import Distribution
from ..plans.planner import TransformPlan, worker_grid

STRATEGIES = ("packed_barrier", "batched_async", "unpacked_direct")
TILE = "dst int, src int, seq int, comp int, o array<int>, n array<int>, re binary, im binary"
TILE_NAMES = [c.split()[0] for c in TILE.split(", ")]
TILE_KINDS = [*[pa.int32()] * 4, *[pa.list_(pa.int32())] * 2, *[pa.binary()] * 2]
TILE_ARROW = pa.schema(list(zip(TILE_NAMES, TILE_KINDS)))
CELLS = "dst int, comp int, ix int, iy int, iz int, re double, im double"
CELLS_ARROW = pa.schema([("dst", pa.int32()), ("comp", pa.int32()), ("ix", pa.int32()), ("iy", pa.int32()), ("iz", pa.int32()), ("re", pa.float64()), ("im", pa.float64())])
#: Component numbers of kernels that travel with the field: KERNEL, KERNEL - 1, ...
KERNEL = -10
#: A kernel's finished spectrum, read from storage at the last forward switch.
READY = -2

Blocks = dict[int, np.ndarray]


def is_kernel(comp: int) -> bool:
    return comp <= KERNEL


class Clock(AccumulatorParam):
    """Seconds that the workers spend, by (step, on the way back, phase)."""

    def zero(self, value: dict) -> dict:
        return {}

    def addInPlace(self, a: dict, b: dict) -> dict:
        for key, seconds in b.items():
            a[key] = a.get(key, 0.0) + seconds
        return a


@dataclass(frozen=True)
class Workers:
    """A worker grid over a plan: who owns what at each step, under one index distribution."""

    plan: TransformPlan
    p: int = 4
    decomposition: str = "pencil"
    distribution: str = "strided"
    #: Workers of a machine; if set, those of the same machine are served first (tried by the reference, without gain).
    node_size: int = 0
    #: An accumulator of :class:`Clock`, or none.
    clock: object = field(default=None, compare=False)
    grid: tuple[int, int] = field(init=False)

    def __post_init__(self):
        object.__setattr__(self, "grid", worker_grid(self.p, self.decomposition))

    def divided(self, step: int) -> tuple[int, int]:
        o = self.plan.order
        return ((o[1], o[2]), (o[0], o[2]), (o[0], o[1]))[step]

    def size(self, axis: int, step: int, kernel: bool = False) -> int:
        """Values along an axis when the line pass of ``step`` begins (forwards) or has just been undone (backwards)."""
        line = self.plan.lines[axis]
        if self.plan.order.index(axis) < step:
            return line.slots
        return line.kernel_points if kernel else line.axis.points

    def ranges(self, worker: int, step: int, kernel: bool = False, done: bool = False) -> list[tuple[int, int]]:
        """(from, to) along each axis; the active axis is whole, and has its modes if its pass is ``done``."""
        out = [(0, self.size(a, step + (done and a == self.plan.order[step]), kernel)) for a in range(3)]
        for axis, parts, mine in zip(self.divided(step), self.grid, divmod(worker, self.grid[1])):
            s = Distribution(self.size(axis, step, kernel), parts, self.distribution).starts()
            out[axis] = (int(s[mine]), int(s[mine + 1]))
        return out

    def owner(self, step: int, columns: list):
        """Owner of a cell, as a column expression."""
        a, b = (Distribution(self.size(axis, step), parts, self.distribution).owner(columns[axis]) for axis, parts in zip(self.divided(step), self.grid))
        return (a * self.grid[1] + b).cast("int")

    def peers(self, worker: int, step: int, to: int) -> list[int]:
        """Receivers of a worker's tiles, in rotated order: it begins with its next neighbour, so no receiver is met by all."""
        row, col = divmod(worker, self.grid[1])
        if {step, to} == {0, 1}:
            found = [r * self.grid[1] + col for r in range(self.grid[0])]
        else:
            found = [row * self.grid[1] + c for c in range(self.grid[1])]
        near = lambda d: bool(self.node_size) and d // self.node_size != worker // self.node_size
        return sorted(found, key=lambda d: (near(d), (d - worker - 1) % self.p))

    def local(self, step: int, to: int) -> bool:
        """Every worker would only send to itself."""
        return self.grid[0 if {step, to} == {0, 1} else 1] == 1


def cut(blocks: Blocks, w: Workers, worker: int, step: int, to: int, tile_bytes: int = 8 << 20) -> Iterator[tuple]:
    """Tiles (a row each) for every receiver, in send order; large ones are cut along their first axis."""
    for comp, block in blocks.items():
        mine = [(a, a + n) for a, n in zip(_origin(w, worker, step, comp), block.shape)]
        for seq, dst in enumerate(w.peers(worker, step, to)):
            theirs = w.ranges(dst, to, is_kernel(comp), to < step)
            lo = [max(a[0], b[0]) for a, b in zip(mine, theirs)]
            hi = [min(a[1], b[1]) for a, b in zip(mine, theirs)]
            if any(x >= y for x, y in zip(lo, hi)):
                continue
            rows = max(1, int(tile_bytes // max(8, 8 * (hi[1] - lo[1]) * (hi[2] - lo[2]))))
            for x in range(lo[0], hi[0], rows):
                y = min(x + rows, hi[0])
                part = block[x - mine[0][0] : y - mine[0][0], lo[1] - mine[1][0] : hi[1] - mine[1][0], lo[2] - mine[2][0] : hi[2] - mine[2][0]]
                im = b"" if np.iscomplexobj(part) else None
                yield dst, worker, seq, comp, [x, lo[1], lo[2]], list(part.shape), np.ascontiguousarray(part), im


def _origin(w: Workers, worker: int, step: int, comp: int) -> list[int]:
    return [r[0] for r in w.ranges(worker, step, is_kernel(comp))]


class Receiver:
    """A worker's zeroed blocks of the next step, filled tile by tile."""

    def __init__(self, w: Workers, worker: int, step: int, done: bool = False):
        self.w, self.worker, self.step, self.done = w, worker, step, done
        self.blocks: Blocks = {}

    def target(self, comp: int, is_complex: bool) -> tuple[np.ndarray, list[int]]:
        ranges = self.w.ranges(self.worker, self.step, is_kernel(comp), self.done or comp == READY)
        if comp not in self.blocks:
            self.blocks[comp] = np.zeros([b - a for a, b in ranges], complex if is_complex else float)
        elif is_complex and not np.iscomplexobj(self.blocks[comp]):
            self.blocks[comp] = self.blocks[comp].astype(complex)
        return self.blocks[comp], [a for a, _ in ranges]

    def paste(self, comp: int, o: list[int], n: list[int], re, im: bytes | None) -> None:
        block, origin = self.target(comp, im is not None)
        part = np.frombuffer(re, float if im is None else complex).reshape(n)
        block[tuple(slice(a - b, a - b + m) for a, b, m in zip(o, origin, n))] = part

    def paste_cells(self, comp: np.ndarray, at: list[np.ndarray], values: np.ndarray) -> None:
        """Cells that are given twice add up."""
        for c in np.unique(comp):
            mask = comp == c
            block, origin = self.target(int(c), np.iscomplexobj(values))
            flat = np.ravel_multi_index(tuple(x[mask] - b for x, b in zip(at, origin)), block.shape)
            np.add.at(block.reshape(-1), flat, values[mask])


def bytes_column(arrays: list[np.ndarray]) -> pa.Array:
    """Binary values from arrays; a single one is not copied."""
    sizes = [a.nbytes for a in arrays]
    flat = [a.reshape(-1).view(np.uint8) for a in arrays]
    data = flat[0] if len(flat) == 1 else np.concatenate([np.zeros(0, np.uint8), *flat])
    offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(arrays), [None, pa.py_buffer(offsets), pa.py_buffer(data)])


def tile_batch(rows: Iterable[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows)) or [()] * len(TILE_NAMES)
    arrays = [bytes_column(list(c)) if f.name == "re" else pa.array(c, f.type) for c, f in zip(columns, TILE_ARROW)]
    return pa.RecordBatch.from_arrays(arrays, schema=TILE_ARROW)


def own_tiles(blocks: Blocks, w: Workers, worker: int) -> pa.RecordBatch:
    """Spectral blocks of the last step as tiles for the same worker."""
    origin = [a for a, _ in w.ranges(worker, 2, done=True)]
    return tile_batch([(worker, worker, 0, c, origin, list(b.shape), np.ascontiguousarray(b), None) for c, b in blocks.items()])


def cell_columns(blocks: Blocks, w: Workers, worker: int, step: int) -> Iterator[tuple[int, list[np.ndarray], np.ndarray]]:
    for comp, block in blocks.items():
        origin = _origin(w, worker, step, comp)
        at = [x.ravel() + o for x, o in zip(np.indices(block.shape), origin)]
        yield comp, at, block.ravel()


def cell_rows(blocks: Blocks, w: Workers, worker: int, step: int, to: int) -> Iterator[pa.RecordBatch]:
    """Every value as a row with its receiver."""
    for comp, at, value in cell_columns(blocks, w, worker, step):
        owner = np.zeros(len(value), np.int64)
        for axis, parts, weight in zip(w.divided(to), w.grid, (w.grid[1], 1)):
            owner += Distribution(w.size(axis, to, is_kernel(comp)), parts, w.distribution).owners()[at[axis]] * weight
        im = pa.array(value.imag) if np.iscomplexobj(value) else pa.nulls(len(value), pa.float64())
        arrays = [pa.array(owner.astype(np.int32)), pa.array(np.full(len(value), comp, np.int32)), *[pa.array(x.astype(np.int32)) for x in at], pa.array(np.ascontiguousarray(value.real)), im]
        yield pa.RecordBatch.from_arrays(arrays, schema=CELLS_ARROW)


def tiles_as_cells(tiles: DataFrame) -> DataFrame:
    """Real tiles as rows of their cells."""

    def run(batches):
        for b in batches:
            heads = zip(*(b.column(c).to_pylist() for c in ("dst", "comp", "o", "n")))
            for (dst, comp, o, n), re in zip(heads, b.column("re")):
                at = [(x + k).ravel().astype(np.int32) for x, k in zip(np.indices(n), o)]
                value = np.frombuffer(re.as_buffer())
                same = [pa.array(np.full(len(value), x, np.int32)) for x in (dst, comp)]
                yield pa.RecordBatch.from_arrays([*same, *map(pa.array, at), pa.array(value), pa.nulls(len(value), pa.float64())], schema=CELLS_ARROW)

    return tiles.mapInArrow(run, CELLS)


Work = Callable[[Blocks, int], Blocks]


#: Bytes of tiles that ``packed_barrier`` hands over in one message, so that no Arrow column outgrows its offsets.
MESSAGE_BYTES = 1 << 30


def _emit(blocks: Blocks, w: Workers, worker: int, step: int, to: int, strategy: str, batch: int) -> Iterator[pa.RecordBatch]:
    if strategy == "unpacked_direct":
        yield from cell_rows(blocks, w, worker, step, to)
        return
    tiles = cut(blocks, w, worker, step, to)
    if strategy == "packed_barrier":
        tiles, batch = iter(list(tiles)), 1 << 30
    held, size = [], 0
    for tile in tiles:
        held.append(tile)
        size += tile[6].nbytes
        if len(held) == batch or size >= MESSAGE_BYTES:
            yield tile_batch(held)
            held, size = [], 0
    if held:
        yield tile_batch(held)


def sent_schema(strategy: str) -> str:
    return CELLS if strategy == "unpacked_direct" else TILE


Finish = Callable[[Blocks, int], Iterator[pa.RecordBatch]]


def switch(sent: DataFrame, w: Workers, step: int, work: Work, finish: Finish, schema: str, strategy: str, done: bool = False) -> DataFrame:
    """Receive at ``step`` (``done``: on the way back), apply ``work`` to each worker's blocks and let ``finish`` emit the outcome."""
    clock = w.clock

    def absorb(batches):
        held: dict[int, Receiver] = {}
        spent = {"communication": 0.0, "copy": 0.0, "compute": 0.0}
        last = time.perf_counter()

        def lap(phase: str) -> None:
            nonlocal last
            now = time.perf_counter()
            spent[phase] += now - last
            last = now

        paste = _paste_cells if strategy == "unpacked_direct" else _paste_tiles
        waiting = []
        for b in batches:
            lap("communication")
            if strategy == "packed_barrier":
                # nothing is pasted before all tiles have come
                waiting.append(b)
            else:
                paste(b, held, w, step, done)
                lap("copy")
        lap("communication")
        while waiting:
            paste(waiting.pop(), held, w, step, done)
        lap("copy")
        for worker in sorted(held):
            blocks = work(held.pop(worker).blocks, worker)
            lap("compute")
            for batch in finish(blocks, worker):
                lap("copy")
                yield batch
                lap("communication")
            lap("copy")
        if clock is not None:
            clock.add({(step, done, phase): seconds for phase, seconds in spent.items()})

    return sent.repartitionById(w.p, F.col("dst")).mapInArrow(absorb, schema)


def _paste_tiles(b: pa.RecordBatch, held: dict[int, Receiver], w: Workers, step: int, done: bool) -> None:
    heads = zip(*(b.column(c).to_pylist() for c in ("dst", "comp", "o", "n", "im")))
    for (dst, comp, o, n, im), re in zip(heads, b.column("re")):
        if dst not in held:
            held[dst] = Receiver(w, dst, step, done)
        held[dst].paste(comp, o, n, re.as_buffer(), im)


def _paste_cells(b: pa.RecordBatch, held: dict[int, Receiver], w: Workers, step: int, done: bool) -> None:
    dsts, comp = b.column("dst").to_numpy(), b.column("comp").to_numpy()
    at = [b.column(c).to_numpy() for c in ("ix", "iy", "iz")]
    re, im = b.column("re").to_numpy(), b.column("im")
    given = im.is_valid().to_numpy(zero_copy_only=False)
    both = re if not given.any() else re + 1j * im.fill_null(0.0).to_numpy()
    for dst in np.unique(dsts):
        if dst not in held:
            held[int(dst)] = Receiver(w, int(dst), step, done)
        for cut_ in (given, ~given):
            mask = (dsts == dst) & cut_
            if mask.any():
                held[int(dst)].paste_cells(comp[mask], [x[mask] for x in at], both[mask] if cut_ is given else re[mask])


def start(cells: DataFrame, w: Workers, work: Work, strategy: str, batch: int, to: int = 1) -> DataFrame:
    """Cells (ix, iy, iz, comp, v) to the first step's workers, their line pass, and the tiles of the next switch."""
    dealt = cells.select(w.owner(0, [F.col("ix"), F.col("iy"), F.col("iz")]).alias("dst"), "comp", "ix", "iy", "iz", F.col("v").cast("double").alias("re"), F.lit(None).cast("double").alias("im"))

    def finish(blocks: Blocks, worker: int):
        yield from _emit(blocks, w, worker, to - 1, to, strategy, batch)

    return switch(dealt, w, 0, work, finish, sent_schema(strategy), "unpacked_direct")


def generate(spark: SparkSession, w: Workers, make: Callable[[int], Blocks], strategy: str, batch: int, to: int = 1) -> DataFrame:
    """Tiles of blocks that every worker makes by itself (kernels, analytic fields)."""

    def run(batches):
        for b in batches:
            for worker in b.column("id").to_pylist():
                yield from _emit(make(worker), w, worker, to - 1, to, strategy, batch)

    return spark.range(0, w.p, 1, w.p).mapInArrow(run, sent_schema(strategy))


def onward(sent: DataFrame, w: Workers, step: int, to: int, work: Work, strategy: str, batch: int, done: bool = False) -> DataFrame:
    def finish(blocks: Blocks, worker: int):
        yield from _emit(blocks, w, worker, step, to, strategy, batch)

    return switch(sent, w, step, work, finish, sent_schema(strategy), strategy, done)


# what a switch will do, as tables


def block_table(spark: SparkSession, w: Workers, step: int, to: int) -> DataFrame:
    """Every block of a switch (src, dst, offset, shape, bytes), by a range-overlap join of the two ownership tables."""

    def owners(s: int, name: str) -> DataFrame:
        axes = w.divided(s)
        tables = [Distribution(w.size(a, s), parts, w.distribution).table(spark) for a, parts in zip(axes, w.grid)]
        first, second = (t.select(F.col("worker").alias(f"w{i}"), F.col("first").alias(f"{name}lo{a}"), F.col("after").alias(f"{name}hi{a}")) for i, (t, a) in enumerate(zip(tables, axes)))
        # w.grid[0] * w.grid[1] rows
        both = first.crossJoin(second).withColumn(name, (F.col("w0") * w.grid[1] + F.col("w1")).cast("int")).drop("w0", "w1")
        whole = next(a for a in range(3) if a not in axes)
        return both.withColumn(f"{name}lo{whole}", F.lit(0).cast("long")).withColumn(f"{name}hi{whole}", F.lit(w.size(whole, s)).cast("long"))

    src, dst = owners(step, "src"), owners(to, "dst")
    # the line pass of ``step`` has replaced points by slots along its axis
    done = w.plan.order[step]
    if to > step:
        src = src.withColumn(f"srchi{done}", F.lit(w.plan.lines[done].slots).cast("long"))
    else:
        dst = dst.withColumn(f"dsthi{w.plan.order[to]}", F.lit(w.plan.lines[w.plan.order[to]].slots).cast("long"))
    lo = [F.greatest(f"srclo{a}", f"dstlo{a}") for a in range(3)]
    hi = [F.least(f"srchi{a}", f"dsthi{a}") for a in range(3)]
    joined = src.join(dst, (lo[0] < hi[0]) & (lo[1] < hi[1]) & (lo[2] < hi[2]))
    n = [hi[a] - lo[a] for a in range(3)]
    return joined.select("src", "dst", *[lo[a].alias(f"o{a}") for a in range(3)], *[n[a].alias(f"n{a}") for a in range(3)], (8 * n[0] * n[1] * n[2]).alias("bytes"))


def send_schedule(spark: SparkSession, p: int, order: str = "rotated") -> DataFrame:
    """(src, round, dst): in the naive order all begin with worker 0, in the rotated one each begins with its neighbour."""
    grid = spark.range(p * p).select(F.floor(F.col("id") / p).cast("int").alias("src"), (F.col("id") % p).cast("int").alias("round"))
    dst = F.col("round") if order == "naive" else F.pmod(F.col("src") + F.col("round") + 1, F.lit(p))
    return grid.select("src", "round", dst.cast("int").alias("dst"))


def fan_in(schedule: DataFrame) -> DataFrame:
    """Most senders that meet at one receiver, by round."""
    return schedule.groupBy("round", "dst").agg(F.count("*").alias("senders")).groupBy("round").agg(F.max("senders").alias("max_fan_in"))
