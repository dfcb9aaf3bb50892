"""Poisson and curl-Poisson solves of table cubes and lines, kernel tables, and convergence of analytic cases."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.transforms_sql import basis, dense_solve_3d, spectral_factor
from ..operators import kernels, metrics, poisson, vortex
from ..operators.baselines import cell_shuffle_fft, direct_sum, monolithic_fft, monolithic_solve
from ..operators.exchange import STRATEGIES
from ..operators.poisson import Options
from ..plans.grid import CELL, EVEN, NODE, ODD, PAIRS, PERIODIC, UNBOUNDED, Axis, GridSpec
from ..plans.planner import build
from ..queries import query, rounded
from ..sources import analytic
from ..sources.fields import components_lineitem, cube_events, cube_lineitem, cube_orders, day, dense, table
from . import published

N = 8
C1 = "SELECT CAST(l_partkey % 8 AS BIGINT) AS ix, CAST(l_suppkey % 8 AS BIGINT) AS iy, CAST(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) % 8 AS BIGINT) AS iz, sum(l_extendedprice * (1 - l_discount) / 1e6) AS v FROM lineitem GROUP BY 1, 2, 3"
C2 = "SELECT CAST(floor(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) * 8 / 30) AS BIGINT) AS ix, CAST(floor(hour(ts) * 8 / 24) AS BIGINT) AS iy, CAST(json_extract_string(props, '$.k') AS INT) % 8 AS iz, sum(value / 1e3) AS v FROM events GROUP BY 1, 2, 3"
C3 = "SELECT CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) % 8 AS BIGINT) AS ix, CAST(o_custkey % 8 AS BIGINT) AS iy, CAST(o_orderkey % 8 AS BIGINT) AS iz, sum(o_totalprice / 1e6) AS v FROM orders GROUP BY 1, 2, 3"


def rounded_cells(df: DataFrame, *extra: str) -> DataFrame:
    return df.select(*extra, "ix", "iy", "iz", rounded("v").alias("v"))


def _cells_sql(body: str, extra: str = "") -> str:
    return f"SELECT {extra}CAST(ix AS INT) AS ix, CAST(iy AS INT) AS iy, CAST(iz AS INT) AS iz, round(v, 6) + 0.0 AS v FROM ({body}) solved"


def spectral_grid(n: int = N) -> GridSpec:
    return GridSpec.of(Axis(n, EVEN, EVEN, CELL), Axis(n, ODD, EVEN, CELL), Axis(n, PERIODIC, PERIODIC, CELL))


@query("poisson3d_spectral_lineitem", _cells_sql(dense_solve_3d(C1, ("ee", "oe", "pp"), N, 1 / N, spectral_factor("gauss4", 1 / N))))
def poisson3d_spectral_lineitem(spark, sf_dir):
    return rounded_cells(poisson.solve(cube_lineitem(spark, sf_dir), spectral_grid(), "gauss4"))


# one axis: the four symmetric pairs and the periodic one

DAYS = "SELECT o_orderpriority AS key, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) % 64 AS BIGINT) AS j, sum(o_totalprice / 1e6) AS v FROM orders GROUP BY 1, 2"


def daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(priority, ix, v) over 64 bins; priorities become components of one solve."""
    o = table(spark, sf_dir, "orders")
    number = F.substring("o_orderpriority", 1, 1).cast("int")
    return o.groupBy(number.alias("comp"), F.pmod(day("o_orderdate", "1995-01-01"), F.lit(64)).cast("int").alias("ix")).agg(F.sum(F.col("o_totalprice") / 1e6).alias("v")).withColumn("iy", F.lit(0)).withColumn("iz", F.lit(0))


def _line_result(df: DataFrame) -> DataFrame:
    return df.select(F.col("comp").alias("priority"), F.col("ix").alias("j"), rounded("v").alias("v"))


def _one_axis():
    pairs = {"periodic": ("pp", PERIODIC, PERIODIC), "even_even": ("ee", EVEN, EVEN), "odd_odd": ("oo", ODD, ODD), "odd_even": ("oe", ODD, EVEN), "even_odd": ("eo", EVEN, ODD)}
    for name, (kind, left, right) in pairs.items():
        sql = f"""WITH f AS ({DAYS}), b AS ({basis(kind, 64, 1 / 64)}), c AS (SELECT key, m, sum(v * b * w) AS c FROM f JOIN b USING (j) GROUP BY key, m)
        SELECT CAST(substr(key, 1, 1) AS INT) AS priority, CAST(j AS INT) AS j, round(sum(c * b * CASE WHEN o > 0 THEN -1.0 / (o * o) ELSE 0.0 END), 6) + 0.0 AS v FROM c JOIN b USING (m) GROUP BY key, j"""

        def run(spark, sf_dir, left=left, right=right):
            spec = GridSpec.of(Axis(64, left, right, CELL))
            return _line_result(poisson.solve(daily(spark, sf_dir), spec, "singular", Options(workers=1)))

        query(f"poisson1d_{name}_orders", sql)(run)


_one_axis()


@query("poisson1d_unbounded_events", f"WITH f AS (SELECT event_type, CAST(date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) // 12 AS BIGINT) AS j, sum(value) * 0.00123456789 AS v FROM events GROUP BY 1, 2), i AS (SELECT CAST(range AS BIGINT) AS i FROM range(0, 60)) SELECT event_type, CAST(i AS INT) AS j, round(sum(abs(i - j) / 60.0 / 2 * v) / 60, 6) + 0.0 AS v FROM f CROSS JOIN i GROUP BY event_type, i")
def poisson1d_unbounded_events(spark, sf_dir):
    """The kernel |x| / 2 over half days, an event type a component."""
    return _event_lines(spark, sf_dir, UNBOUNDED, UNBOUNDED)


def _event_lines(spark: SparkSession, sf_dir: str, left: str, right: str) -> DataFrame:
    types = ["click", "error", "purchase", "signup", "view"]
    half = F.floor((F.unix_timestamp("ts") - F.unix_timestamp(F.lit("2024-01-01").cast("timestamp"))) / 43200).cast("int")
    comp = F.array_position(F.array(*map(F.lit, types)), F.col("event_type")).cast("int")
    e = table(spark, sf_dir, "events").groupBy(comp.alias("comp"), half.alias("ix")).agg((F.sum("value") * 0.00123456789).alias("v")).withColumn("iy", F.lit(0)).withColumn("iz", F.lit(0))
    u = poisson.solve(e, GridSpec.of(Axis(60, left, right, CELL)), "singular", Options(workers=1))
    return u.select(F.element_at(F.array(*map(F.lit, types)), F.col("comp")).alias("event_type"), F.col("ix").alias("j"), rounded("v").alias("v"))


@query("poisson1d_semi_orders", f"WITH f AS ({DAYS}), i AS (SELECT CAST(range AS BIGINT) AS i FROM range(0, 64)) SELECT CAST(substr(key, 1, 1) AS INT) AS priority, CAST(i AS INT) AS j, round(sum((abs(i - j) - abs(i + j + 1)) / 64.0 / 2 * v) / 64, 6) + 0.0 AS v FROM f CROSS JOIN i GROUP BY key, i")
def poisson1d_semi_orders(spark, sf_dir):
    """Odd on the left, open on the right: an image of the opposite sign."""
    return _line_result(poisson.solve(daily(spark, sf_dir), GridSpec.of(Axis(64, ODD, UNBOUNDED, CELL)), "singular", Options(workers=1)))


@query("poisson1d_semi_events", f"WITH f AS (SELECT event_type, CAST(date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) // 12 AS BIGINT) AS j, sum(value) * 0.00123456789 AS v FROM events GROUP BY 1, 2), i AS (SELECT CAST(range AS BIGINT) AS i FROM range(0, 60)) SELECT event_type, CAST(i AS INT) AS j, round(sum((abs(i - j) + abs(i - (119 - j))) / 60.0 / 2 * v) / 60, 6) + 0.0 AS v FROM f CROSS JOIN i GROUP BY event_type, i")
def poisson1d_semi_events(spark, sf_dir):
    """Open on the left, even on the right: an image beyond the last half day."""
    return _event_lines(spark, sf_dir, UNBOUNDED, EVEN)


# three axes, open

_A = (3 / (4 * math.pi)) ** (1 / 3) / N
_ORIGIN = -3 / (8 * math.pi * _A)


def _kernel3(d2: str) -> str:
    return f"CASE WHEN {d2} = 0 THEN {_ORIGIN!r} ELSE -1.0 / (4 * pi() * sqrt({d2}) / {N}) END"


GRID = "(SELECT CAST(x.range AS BIGINT) AS px, CAST(y.range AS BIGINT) AS py, CAST(z.range AS BIGINT) AS pz FROM range(0, 8) x CROSS JOIN range(0, 8) y CROSS JOIN range(0, 8) z)"


@query("poisson3d_unbounded_events", _cells_sql(f"SELECT px AS ix, py AS iy, pz AS iz, sum(v * ({_kernel3('(px - ix) * (px - ix) + (py - iy) * (py - iy) + (pz - iz) * (pz - iz)')})) / {N**3} AS v FROM ({C2}) f CROSS JOIN {GRID} g GROUP BY 1, 2, 3"))
def poisson3d_unbounded_events(spark, sf_dir):
    spec = GridSpec.of(*[Axis(N, UNBOUNDED, UNBOUNDED, CELL)] * 3)
    return rounded_cells(poisson.solve(cube_events(spark, sf_dir), spec, "singular"))


_SEMI = " + ".join(
    f"({'-' if sz < 0 else ''}({_kernel3(f'(px - {x}) * (px - {x}) + (py - iy) * (py - iy) + (pz - {z}) * (pz - {z})')}))"
    for x in ("ix", "(15 - ix)")
    for z, sz in (("iz", 1), ("(-1 - iz)", -1))
)


@query("poisson3d_semi_orders", _cells_sql(f"SELECT px AS ix, py AS iy, pz AS iz, sum(v * ({_SEMI})) / {N**3} AS v FROM ({C3}) f CROSS JOIN {GRID} g GROUP BY 1, 2, 3"))
def poisson3d_semi_orders(spark, sf_dir):
    """Open-even in x, open in y, odd-open in z: images of one sign in x, of the other in z."""
    spec = GridSpec.of(Axis(N, UNBOUNDED, EVEN, CELL), Axis(N, UNBOUNDED, UNBOUNDED, CELL), Axis(N, ODD, UNBOUNDED, CELL))
    return rounded_cells(poisson.solve(cube_orders(spark, sf_dir), spec, "singular"))


# curl

CURL_KINDS = [("ee", "oo", "oo"), ("oo", "ee", "oo"), ("oo", "oo", "ee")]
_STEPS = {"spectral": "o{a}", "fd2": "sin(o{a} * {h}) / {h}", "fd4": "(4.0 / 3 * sin(o{a} * {h}) - sin(2 * o{a} * {h}) / 6) / {h}", "fd6": "(1.5 * sin(o{a} * {h}) - 0.3 * sin(2 * o{a} * {h}) + sin(3 * o{a} * {h}) / 30) / {h}"}


def curl_grids(n: int = N) -> list[GridSpec]:
    """Closed walls: the normal component even along its own axis and odd along the others."""
    pair = {"ee": (EVEN, EVEN), "oo": (ODD, ODD)}
    return [GridSpec.of(*[Axis(n, *pair[k], CELL) for k in kinds]) for kinds in CURL_KINDS]


def _curl_sql() -> str:
    parts = []
    for derivative, step in _STEPS.items():
        for out, terms in enumerate(vortex.CURL):
            for sign, axis, comp in terms:
                kinds = CURL_KINDS[comp]
                flipped = tuple(("ee" if k == "oo" else "oo") if a == axis else k for a, k in enumerate(kinds))
                size = step.format(a="xyz"[axis], h=repr(1 / N))
                turn = sign * (1 if kinds[axis] == "oo" else -1)
                cells = f"SELECT ix, iy, iz, sum(p[{comp + 1}]) AS v FROM (SELECT CAST(l_partkey % 8 AS BIGINT) AS ix, CAST(l_suppkey % 8 AS BIGINT) AS iy, CAST(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) % 8 AS BIGINT) AS iz, [l_extendedprice / 1e6 * l_tax, l_extendedprice / 1e6 * l_discount, l_extendedprice / 1e6] AS p FROM lineitem) l GROUP BY 1, 2, 3"
                factor = f"{turn} * ({size}) * ({spectral_factor('gauss4', 1 / N)})"
                parts.append(f"SELECT '{derivative}' AS derivative, {out} AS comp, ix, iy, iz, v FROM ({dense_solve_3d(cells, kinds, N, 1 / N, factor, flipped)}) t")
    return "SELECT derivative, CAST(comp AS INT) AS comp, CAST(ix AS INT) AS ix, CAST(iy AS INT) AS iy, CAST(iz AS INT) AS iz, round(sum(v), 6) + 0.0 AS v FROM (" + " UNION ALL ".join(parts) + ") p GROUP BY 1, 2, 3, 4, 5"


@query("curl_poisson_lineitem", _curl_sql())
def curl_poisson_lineitem(spark, sf_dir):
    """lap(u) = curl(f) for three measures as components, with all four derivatives."""
    u = vortex.solve_each(components_lineitem(spark, sf_dir), curl_grids(), ["gauss4"], vortex.DERIVATIVES)
    return rounded_cells(u, "derivative", "comp")


# kernels in mode space

_MODES = "(SELECT CAST(x.range AS INT) AS kx, CAST(y.range AS INT) AS ky, CAST(z.range AS INT) AS kz, pi() * x.range AS ox, pi() * (y.range + 0.5) AS oy, 2 * pi() * z.range AS oz FROM range(0, 9) x CROSS JOIN range(0, 8) y CROSS JOIN range(0, 5) z)"


#: Kernels that are applied to the line items; the others are listed on the mode grid alone.
APPLIED = ("cutoff", "gauss10", "gauss2", "gauss4", "gauss6")
_QUANTITIES = "(SELECT (l_partkey % 9 + 9) % 9 AS ix, (l_suppkey % 8 + 8) % 8 AS iy, (date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) % 5 + 5) % 5 AS iz, sum(l_quantity) / 1e3 AS c FROM lineitem GROUP BY 1, 2, 3)"


def quantities(spark: SparkSession, sf_dir: str, slots: tuple[int, int, int]) -> DataFrame:
    """(kx, ky, kz, c): quantities of the line items in thousands, as coefficients of the modes that their numbers and days choose."""
    nx, ny, nz = (F.lit(n) for n in slots)
    keys = [F.pmod("l_partkey", nx), F.pmod("l_suppkey", ny), F.pmod(day("l_shipdate", "1995-01-01"), nz)]
    t = table(spark, sf_dir, "lineitem").groupBy(*[k.cast("int").alias(n) for k, n in zip(keys, ("kx", "ky", "kz"))])
    return t.agg((F.sum("l_quantity") / 1e3).alias("c"))


def _kernel_tables():
    for k in kernels.KERNELS:

        def run(spark, sf_dir, k=k):
            g = poisson.spectrum(spark, spectral_grid(), k)
            if k not in APPLIED:
                return g.select("kx", "ky", "kz", rounded("re").alias("g"))
            lines = build(spectral_grid()).lines
            c = quantities(spark, sf_dir, tuple(lines[a].slots for a in range(3)))
            product = F.col("re") * F.coalesce("c", F.lit(0.0))
            return g.join(c, ["kx", "ky", "kz"], "left").select("kx", "ky", "kz", rounded("re").alias("g"), rounded(product).alias("v"))

        g = spectral_factor(k, 1 / N)
        applied = f", round(({g}) * coalesce(c, 0), 6) + 0.0 AS v FROM {_MODES} m LEFT JOIN {_QUANTITIES} q ON ix = kx AND iy = ky AND iz = kz" if k in APPLIED else f" FROM {_MODES} m"
        query(f"kernel_table_{k}", f"SELECT kx, ky, kz, round({g}, 6) + 0.0 AS g{applied}")(run)


_kernel_tables()


# equalities

STRATEGY_CASES = [(s, d) for s in ("packed_barrier", "batched_async", "unpacked_direct") for d in ("pencil", "slab")]


@query("strategy_equivalence", "SELECT strategy, decomposition, 0.0 + round(0.0, 6) AS difference FROM (VALUES ('packed_barrier'), ('batched_async'), ('unpacked_direct')) a(strategy) CROSS JOIN (VALUES ('pencil'), ('slab')) b(decomposition)")
def strategy_equivalence(spark, sf_dir):
    """Largest difference from the first strategy's result: exactly zero for each exchange and decomposition."""
    f, spec = cube_lineitem(spark, sf_dir), spectral_grid()
    first = poisson.solve(f, spec, "gauss4", Options(*STRATEGY_CASES[0], workers=6))
    out = None
    for s, d in STRATEGY_CASES:
        u = poisson.solve(f, spec, "gauss4", Options(s, d, 6 if d == "pencil" else 4))
        e = metrics.e_inf(u, first, ["ix", "iy", "iz"]).select(F.lit(s).alias("strategy"), F.lit(d).alias("decomposition"), (F.col("e_inf") + 0.0).alias("difference"))
        out = e if out is None else out.unionByName(e)
    return out


@query("distribution_equivalence", "SELECT distribution, 0.0 + round(0.0, 6) AS difference FROM (VALUES ('strided'), ('first_heavy'), ('proportional')) a(distribution)")
def distribution_equivalence(spark, sf_dir):
    f, spec = cube_lineitem(spark, sf_dir), spectral_grid()
    first, out = poisson.solve(f, spec, "gauss4"), None
    for kind in ("strided", "first_heavy", "proportional"):
        u = poisson.solve(f, spec, "gauss4", Options(workers=6, distribution=kind))
        e = metrics.e_inf(u, first, ["ix", "iy", "iz"]).select(F.lit(kind).alias("distribution"), (F.col("e_inf") + 0.0).alias("difference"))
        out = e if out is None else out.unionByName(e)
    return out


def periodic_grid(n: int) -> GridSpec:
    return GridSpec.of(*[Axis(n, layout=CELL)] * 3)


_C1R = f"SELECT CAST(ix AS INT) AS ix, CAST(iy AS INT) AS iy, CAST(iz AS INT) AS iz, round(v, 6) + 0.0 AS v FROM ({C1}) c"


@query("periodic_roundtrip_lineitem", _C1R)
def periodic_roundtrip_lineitem(spark, sf_dir):
    """Forward and backward periodic transform of the cube: the cube itself."""
    return rounded_cells(poisson.round_trip(dense(spark, cube_lineitem(spark, sf_dir), N), periodic_grid(N)))


@query("baseline_monolithic_fft", _C1R)
def baseline_monolithic_fft(spark, sf_dir):
    return rounded_cells(monolithic_fft(spark, cube_lineitem(spark, sf_dir), N))


@query("baseline_cell_shuffle_fft", _C1R)
def baseline_cell_shuffle_fft(spark, sf_dir):
    """Line by line with DataFrame operators alone, forward and back."""
    f = dense(spark, cube_lineitem(spark, sf_dir), N).select("ix", "iy", "iz", F.col("v").alias("re"), F.lit(0.0).alias("im"))
    y = cell_shuffle_fft(cell_shuffle_fft(f, N), N, inverse=True)
    return y.select("ix", "iy", "iz", rounded("re").alias("v"))


@query("baseline_direct_sum", _cells_sql(f"SELECT px AS ix, py AS iy, pz AS iz, sum(v * ({_kernel3('(px - ix) * (px - ix) + (py - iy) * (py - iy) + (pz - iz) * (pz - iz)')})) / {N**3} AS v FROM ({C2}) f CROSS JOIN {GRID} g GROUP BY 1, 2, 3"))
def baseline_direct_sum(spark, sf_dir):
    """The convolution by all pairs of cells."""
    n2 = spark.range(3 * 49 + 1).withColumnRenamed("id", "n2")
    g = n2.withColumn("g", F.when(F.col("n2") == 0, _ORIGIN).otherwise(-1.0 / (4 * math.pi * F.sqrt("n2") / N)) / N**3)
    return rounded_cells(direct_sum(dense(spark, cube_events(spark, sf_dir), N), g))


@query("parseval_lineitem", f"SELECT round(sum(v * v), 6) + 0.0 AS direct, round(sum(v * v), 6) + 0.0 AS spectral FROM ({C1}) c")
def parseval_lineitem(spark, sf_dir):
    from ..plans.planner import build

    f = cube_lineitem(spark, sf_dir)
    out = metrics.parseval(f, poisson.forward(f, periodic_grid(N)), build(periodic_grid(N)))
    return out.select(rounded("direct").alias("direct"), rounded("spectral").alias("spectral"))


@query("linearity_events", "SELECT 0.0 + round(0.0, 6) AS e_inf")
def linearity_events(spark, sf_dir):
    """The solution of two halves of the events adds up to the solution of all."""
    spec = GridSpec.of(*[Axis(N, UNBOUNDED, UNBOUNDED, CELL)] * 3)
    f = cube_events(spark, sf_dir)
    whole = poisson.solve(f, spec, "gauss4")
    parts = [poisson.solve(f.where(p), spec, "gauss4") for p in ("ix % 2 = 0", "ix % 2 = 1")]
    total = parts[0].unionByName(parts[1]).groupBy("ix", "iy", "iz").agg(F.sum("v").alias("v"))
    return metrics.e_inf(total, whole, ["ix", "iy", "iz"]).select(rounded("e_inf").alias("e_inf"))


# convergence of the analytic cases

GAUSS = [k for k in kernels.KERNELS if k.startswith("gauss")]
_K2 = math.pi**2 * (1 + 25 / 4 + 64)
#: Intervals at which the solver runs; the closed form goes on to the largest published grid.
SOLVED = (16, 32, 64)
CLOSED = (128, 256, 512, 1024, 2048)


def _validation_sql() -> str:
    """Errors of the closed case, |1 - symbol| of each kernel at its one wave; none is left by ``singular`` and by ``cutoff``, whose
    wave lies below the cut."""
    sizes = ", ".join(f"({n}, '{how}')" for how, ns in (("solver", SOLVED), ("closed form", CLOSED)) for n in ns)
    rows = []
    for k in kernels.KERNELS:
        if k in ("singular", "cutoff"):
            e = f"CASE WHEN {_K2!r} < pi() * pi() * n * n OR '{k}' = 'singular' THEN 0.0 ELSE 1.0 END"
        elif k == "lattice":
            d2 = " + ".join(f"4.0 * n * n * pow(sin({w}.0 * pi() / n / 4), 2)" for w in (2, 5, 16))
            e = f"abs({_K2!r} / ({d2}) - 1)"
        else:
            q = f"({_K2!r} * 2.0 / (n * n))"
            terms, f = ["1.0"], 1
            for j in range(1, int(k[5:]) // 2):
                f *= j
                terms.append(f"pow({q}, {j}) / {f}.0")
            e = f"abs(1 - exp(-{q}) * ({' + '.join(terms)}))"
        rows.append(f"SELECT '{k}' AS kernel, CAST(n AS INT) AS n, how, round({e}, 9) + 0.0 AS error FROM (VALUES {sizes}) v(n, how)")
    return " UNION ALL ".join(rows)


def case_errors(spark: SparkSession, case: str, kinds: list[str], sizes: tuple[int, ...], origin: str = "published", layout: str = NODE, options: Options = Options()) -> DataFrame:
    """(kernel, n, error): E_inf of the distributed solver on an analytic case, all kernels in one solve for each size."""
    out = None
    for n in sizes:
        spec = analytic.case_grid(case, n, layout)
        f, u = analytic.scalar_field(spark, case, spec), analytic.scalar_field(spark, case, spec, "u")
        got = poisson.solve_each(f, spec, kinds, options, origin)
        both = got.join(u.withColumnRenamed("v", "u"), ["ix", "iy", "iz"])
        e = both.groupBy("kernel").agg(F.max(F.abs(F.col("v") - F.col("u"))).alias("error")).select("kernel", F.lit(n).alias("n"), "error")
        out = e if out is None else out.unionByName(e)
    return out


@query("validation_spectral_errors", _validation_sql())
def validation_spectral_errors(spark, sf_dir):
    """Errors of the closed case equal |1 - symbol| of each kernel: by the solver up to 64 intervals, by the kernel's column expression at
    the case's one wave up to 2048."""
    kinds = list(kernels.KERNELS)
    solved = case_errors(spark, "spectral", kinds, SOLVED).withColumn("how", F.lit("solver"))
    out = solved
    wave = spark.createDataFrame([(1, 2, 4)], "kx int, ky int, kz int")
    for n in CLOSED:
        for k in kinds:
            g = poisson.closed_form(wave, analytic.case_grid("spectral", n), k)
            out = out.unionByName(g.select(F.lit(k).alias("kernel"), F.lit(n).alias("n"), F.abs(F.col("re") * _K2 + 1).alias("error"), F.lit("closed form").alias("how")))
    return out.select("kernel", "n", "how", rounded("error", 9).alias("error"))


def _digits(column: str) -> str:
    """Three decimals of the mantissa and the power of ten: as much as the published digits and two summation orders share."""
    return f"round({column} / pow(10.0, floor(log10({column}))), 3) + 0.0 AS mantissa, CAST(floor(log10({column})) AS INT) AS exponent"


def _published_errors(errors: dict[str, tuple], least: float = 1e-9) -> str:
    """(kernel, n, error) of the published values above ``least``; below it they are round-off."""
    rows = [(k, n, e) for k, values in errors.items() for n, e in zip((32, 64), values) if e > least]
    return "(SELECT * FROM (VALUES " + ", ".join(f"('{k}', {n}, CAST({e!r} AS DOUBLE))" for k, n, e in rows) + ") v(kernel, n, error))"


def _ordered(errors: str, by: str = "") -> str:
    return f"SELECT {by}kernel, CAST(n AS INT) AS n, {_digits('error')}, round(log2(lag(error) OVER (PARTITION BY {by}kernel ORDER BY n) / error), 2) + 0.0 AS convergence_order FROM {errors} e"


def _with_order(df: DataFrame, by: list[str]) -> DataFrame:
    """Mantissa, exponent and order of convergence of (by.., n, error)."""
    p = metrics.order(df.where("error > 1e-9"), by)
    power = F.floor(F.log10("error"))
    mantissa = rounded(F.col("error") / F.pow(F.lit(10.0), power), 3).alias("mantissa")
    return p.select(*by, "n", mantissa, power.cast("int").alias("exponent"), rounded("order", 2).alias("convergence_order"))


@query("validation_unbounded_orders", _ordered(_published_errors(published.ERRORS)))
def validation_unbounded_orders(spark, sf_dir):
    """The open case at 33 and 65 points, all kernels: the published errors and orders."""
    return _with_order(case_errors(spark, "unbounded", list(published.ERRORS), (32, 64)), ["kernel"])


@query("validation_semi_orders", _ordered(_published_errors(published.SEMI)))
def validation_semi_orders(spark, sf_dir):
    """The half-open case at 33 and 65 points, all kernels: the published errors and orders."""
    return _with_order(case_errors(spark, "semi", list(published.SEMI), (32, 64)), ["kernel"])


_TUBE = "(" + " UNION ALL ".join(f"SELECT '{d}' AS derivative, * FROM {_published_errors(e)} {d}" for d, e in published.TUBE.items()) + ")"


@query("vortex_tube_errors", _ordered(_TUBE, "derivative, "))
def vortex_tube_errors(spark, sf_dir):
    """The tube's velocity at 33 and 65 points, all derivatives and all kernels whose figures are published and not broken off."""
    wanted = spark.createDataFrame([(d, k) for d, e in published.TUBE.items() for k in e], "derivative string, kernel string")
    kinds, out = list(published.TUBE["spectral"]), None
    for n in (32, 64):
        specs = analytic.tube_grids(n, 2)
        f, u = analytic.tube_field(spark, specs[0]), analytic.tube_field(spark, specs[0], "u")
        got = vortex.solve_each(f, specs, kinds, vortex.DERIVATIVES)
        both = got.join(u.withColumnRenamed("v", "u"), ["ix", "iy", "iz", "comp"])
        e = both.groupBy("derivative", "kernel").agg(F.max(F.abs(F.col("v") - F.col("u"))).alias("error")).withColumn("n", F.lit(n))
        out = e if out is None else out.unionByName(e)
    # as many rows as published series
    return _with_order(out.join(F.broadcast(wanted), ["derivative", "kernel"]), ["derivative", "kernel"])


# every pair of choices


def sweep_cases() -> list[tuple]:
    """(case, boundaries, layout, kernel, strategy, decomposition): every pair of values of any two of the seven choices (three boundary
    pairs, layout, kernel, switch, decomposition) stands in some case. Cases are built one by one, each from the pair that is still
    missing with the most companions, its other choices taken to cover most missing pairs."""
    levels = [list(PAIRS)] * 3 + [[CELL, NODE], list(kernels.KERNELS), list(STRATEGIES), ["pencil", "slab"]]
    sizes = [len(x) for x in levels]
    missing = {(a, i, b, j) for a in range(7) for b in range(a + 1, 7) for i in range(sizes[a]) for j in range(sizes[b])}

    def gain(row: dict[int, int], a: int, i: int) -> int:
        return sum(((a, i, b, j) if a < b else (b, j, a, i)) in missing for b, j in row.items())

    out = []
    while missing:
        a, i, b, j = min(missing)
        row = {a: i, b: j}
        for c in range(7):
            if c not in row:
                # of equal gains the one that has come least recently
                row[c] = max(range(sizes[c]), key=lambda k: (gain(row, c, k), -((k - len(out)) % sizes[c])))
        missing -= {(c, row[c], d, row[d]) for c in range(7) for d in range(c + 1, 7)}
        triple = [levels[c][row[c]] for c in range(3)]
        out.append((len(out), triple, *(levels[c][row[c]] for c in range(3, 7))))
    return out


def _sweep_sql() -> str:
    rows = ", ".join(f"({c}, '{' '.join('-'.join(p) for p in t)}', '{layout}', '{k}', '{s}', '{d}')" for c, t, layout, k, s, d in sweep_cases())
    return f'SELECT CAST(c AS INT) AS "case", boundaries, layout, kernel, strategy, decomposition, 0.0 + round(0.0, 6) AS difference FROM (VALUES {rows}) v(c, boundaries, layout, kernel, strategy, decomposition)'


#: Cases whose solves are one job.
TOGETHER = 15


def sweep_fields(spark: SparkSession, sf_dir: str) -> dict[str, np.ndarray]:
    """The line items' cube on the points of either layout, brought to mean 0 and deviation 1 so that no mode hides the others."""
    out = {}
    for layout in (CELL, NODE):
        n = Axis(N, EVEN, EVEN, layout).points
        f = np.zeros((n, n, n))
        # sums in 512 or 729 cells
        for c in dense(spark, cube_lineitem(spark, sf_dir, n), n).collect():
            f[c.ix, c.iy, c.iz] = c.v
        f -= f.mean()
        out[layout] = f / (f.std() or 1.0)
    return out


@query("combination_sweep", _sweep_sql())
def combination_sweep(spark, sf_dir):
    """A cover of all pairs of choices on 8^3 intervals, each case solved for the line items by Spark and as one array: the largest
    difference is zero. Every case has the cube turned in another way."""
    fields, cases, rows = sweep_fields(spark, sf_dir), sweep_cases(), []
    keys = ["case", "ix", "iy", "iz"]
    for first in range(0, len(cases), TOGETHER):
        got, tables = None, []
        for case, triple, layout, kernel, strategy, decomposition in cases[first : first + TOGETHER]:
            spec = GridSpec.of(*[Axis(N, *p, layout) for p in triple])
            f = np.roll(fields[layout], (case, case // N, case // N**2), (0, 1, 2))
            # the cube's grid of 512 or 729 points
            at = np.indices(spec.shape).reshape(3, -1).astype(np.int32)
            whole = monolithic_solve(f, spec, kernel)
            tables.append(pa.table({"case": np.full(f.size, case, np.int32), "ix": at[0], "iy": at[1], "iz": at[2], "w": whole.ravel()}))
            cells = spark.createDataFrame(pa.table({"ix": at[0], "iy": at[1], "iz": at[2], "v": f.ravel()}))
            u = poisson.solve(cells, spec, kernel, Options(strategy, decomposition, 4)).select(F.lit(case).alias("case"), "ix", "iy", "iz", "v")
            got = u if got is None else got.unionByName(u)
        both = got.join(spark.createDataFrame(pa.concat_tables(tables)), keys, "full")
        difference = F.max(F.abs(F.coalesce("v", F.lit(1e9)) - F.coalesce("w", F.lit(-1e9))))
        # a number for each case
        found = both.groupBy("case").agg(rounded(difference, 9).alias("difference")).orderBy("case").collect()
        rows += [(c, " ".join("-".join(p) for p in cases[c][1]), *cases[c][2:], d) for c, d in found]
    return spark.createDataFrame(rows, "case int, boundaries string, layout string, kernel string, strategy string, decomposition string, difference double")


# where the time goes

_PHASES = [(s, k, p) for s in STRATEGIES for k in range(1, 6) for p in metrics.PHASES]


@query("step_breakdown_events", "SELECT strategy, CAST(line_pass AS INT) AS line_pass, phase, true AS measured FROM (VALUES " + ", ".join(f"('{s}', {k}, '{p}')" for s, k, p in _PHASES) + ") v(strategy, line_pass, phase)")
def step_breakdown_events(spark, sf_dir):
    """Which seconds a solve records: for each strategy, line pass and phase (compute, copy, communication). The seconds themselves,
    which no other engine can repeat, are in the bench; here stands that each was measured."""
    spec, f = GridSpec.of(*[Axis(N, UNBOUNDED, UNBOUNDED, CELL)] * 3), cube_events(spark, sf_dir)
    out = None
    for s in STRATEGIES:
        t = metrics.breakdown(spark, lambda clock, s=s: poisson.solve(f, spec, "gauss4", Options(s, workers=4, clock=clock)), s)
        out = t if out is None else out.unionByName(t)
    return out.select("strategy", "line_pass", "phase", (F.col("seconds") > 0).alias("measured"))
