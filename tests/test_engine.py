import math
from datetime import datetime, timedelta

import numpy as np
import pytest
from pyspark.sql import functions as F

from spectral_spark.functions import special, transforms
from spectral_spark.operators import kernels, metrics, poisson, vortex
from spectral_spark.operators.baselines import monolithic_curl_solve, monolithic_solve, monolithic_spectrum
from spectral_spark.operators.exchange import STRATEGIES, Workers, block_table, fan_in, send_schedule
from spectral_spark.operators.poisson import Options
from spectral_spark.plans.boundary import LineTransform, extend, impose, refill, restrict
from spectral_spark.plans.distribution import Distribution, is_degenerate
from spectral_spark.plans.grid import CELL, EVEN, NODE, ODD, PAIRS, PERIODIC, UNBOUNDED, Axis, GridSpec
from spectral_spark.plans.planner import build, order_axes, padding_factor, switches, worker_grid
from spectral_spark.sources import analytic
from spectral_spark.sources.fields import check_field_schema, dense, lines

SIZES = (1, 2, 3, 4, 5, 8, 16, 24, 31, 64)


def dense_transform(name, kind, n, x):
    """The defining sums."""
    trig = np.cos if name == "dct" else np.sin
    half_k, half_j = kind in (3, 4), kind in (2, 4)
    ks = {("dct", 1): range(n + 1), ("dst", 1): range(1, n), ("dst", 2): range(1, n + 1)}.get((name, kind), range(n))
    js = {("dct", 1): range(n + 1), ("dst", 1): range(1, n), ("dst", 3): range(1, n + 1)}.get((name, kind), range(n))
    ends = {("dct", 1): {0, n}, ("dct", 3): {0}, ("dst", 3): {n}}.get((name, kind), set())
    m = np.array([[(1 if j in ends else 2) * trig(np.pi * (k + half_k / 2) * (j + half_j / 2) / n) for j in js] for k in ks])
    return x @ m.T if len(js) else x


@pytest.mark.parametrize("name", ["dct", "dst"])
@pytest.mark.parametrize("kind", [1, 2, 3, 4])
def test_transforms_equal_their_sums(name, kind):
    r = np.random.default_rng(kind)
    run, back = (transforms.dct, transforms.inverse_dct) if name == "dct" else (transforms.dst, transforms.inverse_dst)
    for n in SIZES:
        size = {("dct", 1): n + 1, ("dst", 1): n - 1}.get((name, kind), n)
        x = r.normal(size=(3, size))
        if not size:
            continue
        assert np.allclose(run(x, kind), dense_transform(name, kind, n, x), atol=1e-11 * n)
        assert np.allclose(back(run(x, kind), kind), x, atol=1e-12)
        z = x + 1j * r.normal(size=x.shape)
        assert np.allclose(run(z, kind), run(z.real, kind) + 1j * run(z.imag, kind))


@pytest.mark.parametrize("layout", [CELL, NODE])
@pytest.mark.parametrize("pair", PAIRS)
def test_line_transforms_invert(layout, pair):
    r = np.random.default_rng(7)
    for n in (1, 2, 3, 4, 7, 8, 16, 33):
        for complex_in in (False, True):
            t = LineTransform(Axis(n, *pair, layout), complex_in)
            x = r.normal(size=(2, t.axis.points)) + (1j * r.normal(size=(2, t.axis.points)) if complex_in else 0)
            if layout == NODE:
                if pair[0] == ODD:
                    x[:, 0] = 0
                if pair[1] == ODD:
                    x[:, -1] = 0
                if pair == (PERIODIC, PERIODIC):
                    x[:, -1] = x[:, 0]
            y = t.forward(x)
            assert y.shape[-1] == t.slots == len(t.modes()) == len(t.omega())
            assert np.allclose(t.backward(y), x, atol=1e-12), (n, complex_in)


def test_distributions_by_brute_force(spark):
    for n in range(0, 200, 7):
        for p in range(1, 40):
            for kind in ("strided", "first_heavy", "proportional"):
                d = Distribution(n, p, kind)
                counts = np.diff(d.starts())
                assert counts.sum() == n and counts.min() >= 0 and counts.max() - counts.min() <= 1
            assert is_degenerate(n, p) == bool(np.array_equal(Distribution(n, p).starts(), Distribution(n, p, "first_heavy").starts())) or n % p == 0 or p // (n % p) > 1
    for n, p in ((32, 7), (32, 6), (1281, 48), (1281, 32), (5, 16), (100, 10), (199, 39)):
        for kind in ("strided", "first_heavy", "proportional"):
            d = Distribution(n, p, kind)
            got = [r.o for r in spark.range(n).select(d.owner(F.col("id")).alias("o")).collect()]
            assert got == d.owners().tolist(), (n, p, kind)
            t = d.table(spark).orderBy("worker").collect()
            assert [x["first"] for x in t] == d.starts()[:-1].tolist() and [x["after"] for x in t] == d.starts()[1:].tolist()
    assert np.diff(Distribution(32, 7).starts()).tolist() == [5, 5, 5, 5, 4, 4, 4]
    assert Distribution(32, 7).owners()[[14, 27]].tolist() == [2, 5]
    assert np.diff(Distribution(32, 6).starts()).tolist() == [5, 5, 6, 5, 5, 6]


def test_planner():
    spec = GridSpec.of(Axis(8, UNBOUNDED, UNBOUNDED), Axis(8, EVEN, ODD), Axis(8, PERIODIC, PERIODIC))
    assert order_axes(spec) == (1, 2, 0) and switches(spec, 1) == 2 and switches(spec, 0) == 3
    assert padding_factor(GridSpec.of(*[Axis(8, UNBOUNDED, UNBOUNDED)] * 3)) == pytest.approx(14 / 3)
    assert worker_grid(12) == (3, 4) and worker_grid(12, "slab") == (1, 12) and worker_grid(7) == (1, 7)
    with pytest.raises(ValueError):
        GridSpec.of(Axis(8), Axis(9))
    with pytest.raises(ValueError):
        Axis(8, PERIODIC, EVEN)


# E_inf at 33 points per axis, as published
GOLDEN = {
    "spectral": {"lattice": 0.04787236290513, "gauss2": 0.7467696399733, "gauss4": 0.3989689609666, "gauss6": 0.1601245500817, "gauss8": 0.0507771449839, "gauss10": 0.01323119103844},
    "unbounded": {"singular": 0.05263276045406, "lattice": 0.01129626253568, "gauss2": 0.3436999189742, "gauss4": 0.09598811809279, "gauss6": 0.02320067531128, "gauss8": 0.004859683170374, "gauss10": 0.0008616949130498, "cutoff": 2.524183947512e-08},
    "semi": {"singular": 0.05167547510286, "gauss2": 0.3378443212264, "gauss4": 0.09399061603496, "gauss6": 0.02265987189851, "gauss8": 0.004741994534202, "gauss10": 0.0009236551104396, "cutoff": 3.817465100572e-08},
}
TUBE = {
    "spectral": {"singular": 0.02560729532124, "gauss2": 0.7114351040324, "gauss4": 0.3624430263832, "gauss6": 0.182082010645, "gauss8": 0.1064721771105, "gauss10": 0.06229027016928},
    "fd2": {"singular": 0.100294, "gauss2": 0.732027, "gauss4": 0.403613, "gauss6": 0.238435, "gauss8": 0.158454, "gauss10": 0.121591},
    "fd4": {"singular": 0.03543, "gauss2": 0.713026, "gauss4": 0.366316},
    "fd6": {"singular": 0.0268313, "gauss2": 0.71163, "gauss4": 0.362994, "gauss6": 0.183024, "gauss8": 0.108164, "gauss10": 0.0645538},
}


@pytest.mark.parametrize("case", GOLDEN)
def test_published_errors(case):
    spec = analytic.case_grid(case, 32)
    u, f = analytic.scalar_arrays(case, spec)
    for kernel, want in GOLDEN[case].items():
        got = np.abs(monolithic_solve(f, spec, kernel, "published") - u).max()
        assert got == pytest.approx(want, rel=1e-6 if kernel == "cutoff" else 1e-9), kernel
    if case == "spectral":
        assert np.abs(monolithic_solve(f, spec, "singular") - u).max() < 1e-14


@pytest.mark.parametrize("derivative", TUBE)
def test_published_tube_errors(derivative):
    specs = analytic.tube_grids(32, 2)
    f, u = analytic.tube_arrays(specs[0])
    for kernel, want in TUBE[derivative].items():
        got = np.abs(monolithic_curl_solve(f, specs, kernel, derivative) - u).max()
        assert got == pytest.approx(want, rel=1e-9 if derivative == "spectral" else 1e-5), kernel


def test_orders_of_the_compact_tube():
    """Second-order kernels on the printed profile: halving h divides the error by four."""
    e = []
    for n in (32, 64):
        specs = analytic.tube_grids(n, 2)
        f, u = analytic.tube_arrays(specs[0], "compact")
        e.append([np.abs(monolithic_curl_solve(f, specs, k, "spectral") - u).max() for k in ("singular", "gauss4")])
    order = np.log2(np.array(e[0]) / np.array(e[1]))
    assert 1.6 < order[0] < 2.4 and order[1] > 2.5


@pytest.mark.parametrize("kernel,least", [("singular", 1.8), ("gauss4", 3.3), ("lattice", 1.8)])
def test_orders_of_the_open_case(kernel, least):
    e = []
    for n in (32, 64):
        spec = analytic.case_grid("unbounded", n)
        u, f = analytic.scalar_arrays("unbounded", spec)
        e.append(np.abs(monolithic_solve(f, spec, kernel) - u).max())
    assert np.log2(e[0] / e[1]) > least


def as_array(df, shape, comps=1):
    p = df.toPandas()
    out = np.full((comps, *shape), np.nan)
    out[p.comp, p.ix, p.iy, p.iz] = p.v
    return out


@pytest.mark.parametrize("strategy", STRATEGIES)
@pytest.mark.parametrize("decomposition", ["pencil", "slab"])
def test_solves_equal_the_whole_array(spark, strategy, decomposition):
    """Odd sizes, workers that do not divide them, all kinds of axes."""
    r = np.random.default_rng(5)
    for layout, axes in ((NODE, ((EVEN, ODD), (UNBOUNDED, EVEN), (PERIODIC, PERIODIC))), (CELL, ((UNBOUNDED, UNBOUNDED), (ODD, ODD), (ODD, UNBOUNDED)))):
        spec = GridSpec.of(*[Axis(n, *pair, layout, n / 5) for n, pair in zip((5, 6, 7), axes)])
        f = r.normal(size=spec.shape)
        rows = [(*map(int, i), float(v)) for i, v in np.ndenumerate(f)]
        cells = spark.createDataFrame(rows, "ix int, iy int, iz int, v double")
        got = as_array(poisson.solve(cells, spec, "gauss4", Options(strategy, decomposition, 6, batch=2)), spec.shape)[0]
        assert np.array_equal(got, monolithic_solve(f, spec, "gauss4"))


def test_every_boundary_combination_on_one_array():
    """All 1000 triples in both layouts run, and none gives a value that is not finite."""
    r = np.random.default_rng(6)
    for layout in (CELL, NODE):
        for a in PAIRS:
            for b in PAIRS:
                for c in PAIRS:
                    spec = GridSpec.of(*[Axis(2, *p, layout) for p in (a, b, c)])
                    f = r.normal(size=spec.shape)
                    assert np.isfinite(monolithic_solve(f, spec, "gauss2")).all()


def test_semi_unbounded_equals_images():
    """A closed side is an image of the source: even the same sign, odd the opposite."""
    r = np.random.default_rng(8)
    n = 6
    for left, right in ((EVEN, UNBOUNDED), (ODD, UNBOUNDED), (UNBOUNDED, EVEN), (UNBOUNDED, ODD)):
        f = r.normal(size=n)
        spec = GridSpec.of(Axis(n, left, right, CELL))
        got = monolithic_solve(f.reshape(n, 1, 1), spec, "singular").ravel()
        j = np.arange(n)
        image = -1 - j if right == UNBOUNDED else 2 * n - 1 - j
        sign = 1 if EVEN in (left, right) else -1
        want = [sum(abs(i - j) / n / 2 * f + sign * abs(i - image) / n / 2 * f) / n for i in range(n)]
        assert np.allclose(got, want, atol=1e-13)


def test_lattice_solution_inverts_the_difference_laplacian():
    r = np.random.default_rng(9)
    n = 8
    spec = GridSpec.of(*[Axis(n, layout=CELL)] * 3)
    f = r.normal(size=(n, n, n))
    u = monolithic_solve(f, spec, "lattice")
    lap = sum(np.roll(u, 1, a) + np.roll(u, -1, a) - 2 * u for a in range(3)) * n * n
    assert np.allclose(lap, f - f.mean(), atol=1e-10)
    open_spec = GridSpec.of(*[Axis(n, UNBOUNDED, UNBOUNDED, CELL)] * 3)
    u = monolithic_solve(f, open_spec, "lattice")
    inner = u[1:-1, 1:-1, 1:-1]
    lap = sum(np.roll(u, 1, a)[1:-1, 1:-1, 1:-1] + np.roll(u, -1, a)[1:-1, 1:-1, 1:-1] - 2 * inner for a in range(3)) * n * n
    assert np.allclose(lap, f[1:-1, 1:-1, 1:-1], atol=1e-7)


def test_invariants():
    r = np.random.default_rng(10)
    spec = GridSpec.of(Axis(8, layout=CELL), Axis(8, UNBOUNDED, UNBOUNDED, CELL), Axis(8, EVEN, EVEN, CELL))
    f, g = r.normal(size=(2, 8, 8, 8))
    solve = lambda x: monolithic_solve(x, spec, "gauss6")
    assert np.allclose(solve(2 * f + g), 2 * solve(f) + solve(g), atol=1e-12)
    assert np.allclose(solve(np.roll(f, 3, 0)), np.roll(solve(f), 3, 0), atol=1e-12)
    closed = GridSpec.of(*[Axis(8, layout=CELL)] * 3)
    assert abs(monolithic_solve(f, closed, "gauss4").mean()) < 1e-14
    u = monolithic_curl_solve(np.stack([f, g, f * g]), [closed] * 3, "gauss4")
    div = sum(np.fft.ifft(1j * np.where(np.abs(k := np.fft.fftfreq(8) * 8) == 4, 0, k).reshape([-1 if b == a else 1 for b in range(3)]) * 2 * np.pi * np.fft.fft(u[a], axis=a), axis=a).real for a in range(3))
    assert np.abs(div).max() < 1e-10 * max(1, np.abs(u).max())


def test_vortex_in_spark(spark):
    specs = analytic.tube_grids(8, 4)
    f, _ = analytic.tube_arrays(specs[0])
    cells = analytic.tube_field(spark, specs[0])
    for d in vortex.DERIVATIVES:
        got = as_array(vortex.solve(cells, specs, "gauss4", d), specs[0].shape, 3)
        assert np.array_equal(got, monolithic_curl_solve(f, specs, "gauss4", d))
    with pytest.raises(ValueError):
        vortex.out_specs([specs[2], specs[0], specs[2]])


def test_distributed_kernel_spectrum(spark):
    for spec in (analytic.case_grid("unbounded", 4), analytic.case_grid("semi", 4), analytic.case_grid("spectral", 4)):
        for kernel in ("singular", "gauss6", "cutoff"):
            p = poisson.spectrum(spark, spec, kernel).toPandas()
            want = monolithic_spectrum(spec, kernel)
            assert len(p) == want.size and np.allclose(want[p.kx, p.ky, p.kz], p.re, atol=1e-12)


def test_blocks_cover_the_field_once(spark):
    for shape in ((5, 6, 7), (8, 3, 9)):
        spec = GridSpec.of(*[Axis(n, UNBOUNDED, UNBOUNDED, NODE, n / 5) for n in shape])
        w = Workers(build(spec), 6)
        for step, to in ((0, 1), (1, 2), (2, 1), (1, 0)):
            t = block_table(spark, w, step, to).toPandas()
            o = w.plan.order
            size = [w.plan.lines[a].slots if o.index(a) < max(step, to) else spec.axes[a].points for a in range(3)]
            seen = np.zeros(size, int)
            for b in t.itertuples():
                seen[b.o0 : b.o0 + b.n0, b.o1 : b.o1 + b.n1, b.o2 : b.o2 + b.n2] += 1
            assert (seen == 1).all() and t.bytes.sum() == 8 * seen.size
            assert t.groupby("src").dst.nunique().max() <= max(w.grid)


def test_send_order(spark):
    for p in (5, 8):
        rotated = {r["round"]: r.max_fan_in for r in fan_in(send_schedule(spark, p)).collect()}
        naive = {r["round"]: r.max_fan_in for r in fan_in(send_schedule(spark, p, "naive")).collect()}
        assert set(rotated.values()) == {1} and set(naive.values()) == {p} and len(rotated) == p


def test_kernel_functions():
    x = np.array([0.0, 0.3, 1.0, 1.9, 2.1, 7.0, 30.0])
    grid, w = np.polynomial.legendre.leggauss(200)
    for v in x[1:]:
        t = v * (grid + 1) / 2
        assert special.ein(np.array([v]))[0] == pytest.approx(((1 - np.exp(-t)) / t @ w) * v / 2, rel=1e-12)
        assert special.sine_integral(np.array([v]))[0] == pytest.approx((np.sin(t) / t @ w) * v / 2, rel=1e-12)
    assert special.e2(np.array([1.0]))[0] == pytest.approx(0.14849550677592205, rel=1e-12)
    assert special.bessel_k(0, np.array([1.0]))[0] == pytest.approx(0.42102443824070834, rel=1e-12)
    assert special.bessel_k(1, np.array([1.0]))[0] == pytest.approx(0.6019072301972346, rel=1e-12)
    assert special.bessel_j0(np.array([2.404825557695773]))[0] == pytest.approx(0, abs=1e-12)
    i = special.bessel_i_scaled(3, np.array([1.0, 1000.0]))
    assert i[:, 0] == pytest.approx(np.exp(-1) * np.array([1.2660658777520082, 0.565159103992485, 0.13574766976703828, 0.022168424924331902]), rel=1e-12)
    assert i[0, 1] == pytest.approx(0.01261723989186, rel=1e-6)
    # the general quadrature against the closed form on one open axis
    r, k2, h = np.arange(6) * 0.1, np.full(6, 9.0), 0.1
    tau, k = (2 * h) ** 2 / 2, 3.0
    erfc = np.vectorize(math.erfc)
    s = 2 * h
    want = -(np.exp(-k * r) * erfc(k * s / np.sqrt(2) - r / (s * np.sqrt(2))) + np.exp(k * r) * erfc(k * s / np.sqrt(2) + r / (s * np.sqrt(2)))) / (4 * k)
    assert np.allclose(kernels._heat_tail(1, tau, r**2, k2), want, atol=1e-13)


def test_array_columns(spark):
    df = spark.createDataFrame([([1.0, 2.0, 3.0, 4.0, 5.0],), (None,)], "x array<double>")
    odd = Axis(4, ODD, ODD)
    got = df.select(impose(F.col("x"), odd).alias("i"), refill(F.col("x"), Axis(4)).alias("r"), restrict(extend(F.col("x"), Axis(4, UNBOUNDED, EVEN)), Axis(4, UNBOUNDED, EVEN)).alias("e"), F.size(extend(F.col("x"), Axis(4, EVEN, UNBOUNDED))).alias("n"), transforms.dct_column(1)("x").alias("d")).collect()
    assert got[0].i == [0, 2, 3, 4, 0] and got[0].r == [1, 2, 3, 4, 1] and got[0].e == [1, 2, 3, 4, 5] and got[0].n == 9
    assert np.allclose(got[0].d, transforms.dct(np.arange(1.0, 6.0), 1)) and got[1].d is None


def test_fields(spark):
    cells = spark.createDataFrame([(0, 0, 1, 2.0), (1, 1, 1, 3.0)], "ix int, iy int, iz int, v double")
    d = dense(spark, check_field_schema(cells), 2)
    assert d.count() == 8 and d.agg(F.sum("v")).first()[0] == 5.0
    with pytest.raises(TypeError):
        check_field_schema(cells.withColumn("v", F.col("v").cast("float")))
    got = lines(cells.withColumnRenamed("iz", "j"), "ix", 3).orderBy("ix").collect()
    assert [x.line for x in got] == [[0, 2, 0], [0, 3, 0]]
    empty = poisson.solve(cells.limit(0), analytic.case_grid("spectral", 4), "gauss2")
    assert empty.count() == 0


def test_cells_that_do_not_fit(spark):
    """Null values are zero, repeated cells add up, tables need their types; cells outside the grid are an error that names them."""
    from pyspark.errors import PySparkException

    spec = analytic.case_grid("spectral", 4)
    schema = "ix int, iy int, iz int, comp int, v double"
    base = [(1, 2, 3, 0, 2.0), (0, 1, 1, 0, 1.0)]
    table = lambda rows: spark.createDataFrame(rows, schema)
    want = as_array(poisson.solve(table(base), spec), spec.shape)
    for rows in ([*base, (2, 2, 2, 0, None)], [(1, 2, 3, 0, 1.5), (1, 2, 3, 0, 0.5), base[1]]):
        assert np.array_equal(as_array(poisson.solve(table(rows), spec), spec.shape), want)
    for bad in ((5, 0, 0, 0, 1.0), (-1, 0, 0, 0, 1.0), (0, None, 0, 0, 1.0), (0, 0, 99, 0, 1.0), (0, 0, 0, -3, 1.0)):
        for strategy in STRATEGIES:
            with pytest.raises(PySparkException, match="cell outside the grid"):
                poisson.solve(table([*base, bad]), spec, options=Options(strategy)).collect()
    with pytest.raises(TypeError):
        poisson.solve(table(base).withColumn("v", F.col("v").cast("float")), spec)
    assert np.isnan(as_array(poisson.solve(table([*base, (2, 1, 3, 0, float("nan"))]), spec), spec.shape)[0, :, 1:, :]).all()
    with pytest.raises(PySparkException, match="point outside the line"):
        lines(spark.createDataFrame([(1, 7, 1.0)], "key int, j int, v double"), "key", 4).collect()


def test_several_kernels_in_one_solve(spark):
    """The same as one solve for each kernel, open and closed, scalar and curl."""
    kinds = ["singular", "gauss6", "cutoff", "lattice"]
    for case in ("semi", "spectral"):
        spec = analytic.case_grid(case, 6)
        _, f = analytic.scalar_arrays(case, spec)
        got = poisson.solve_each(analytic.scalar_field(spark, case, spec), spec, kinds, Options("batched_async", workers=6)).toPandas()
        for k in kinds:
            p = got[got.kernel == k]
            out = np.zeros(spec.shape)
            out[p.ix, p.iy, p.iz] = p.v
            # the sine integral differs by a rounding between batches of different length
            assert len(p) == out.size and np.allclose(out, monolithic_solve(f, spec, k), rtol=0, atol=1e-15 if k == "cutoff" else 0)
    specs = analytic.tube_grids(6, 3)
    f, _ = analytic.tube_arrays(specs[0])
    got = vortex.solve_each(analytic.tube_field(spark, specs[0]), specs, ["gauss2", "singular"], ("fd2", "spectral")).toPandas()
    for k in ("gauss2", "singular"):
        for d in ("fd2", "spectral"):
            p = got[(got.kernel == k) & (got.derivative == d)]
            out = np.zeros((3, *specs[0].shape))
            out[p.comp, p.ix, p.iy, p.iz] = p.v
            assert np.array_equal(out, monolithic_curl_solve(f, specs, k, d))


def test_sweep_covers_all_pairs():
    from spectral_spark import queries  # noqa: F401
    from spectral_spark.workloads.solves import sweep_cases

    rows = [(*map(tuple, triple), layout, kernel, strategy, kind) for _, triple, layout, kernel, strategy, kind in sweep_cases()]
    levels = [PAIRS] * 3 + [(CELL, NODE), kernels.KERNELS, STRATEGIES, ("pencil", "slab")]
    assert 100 <= len(rows) <= 160
    for a in range(7):
        for b in range(a + 1, 7):
            assert len({(r[a], r[b]) for r in rows}) == len(levels[a]) * len(levels[b])


def test_pending_needs_its_session(spark):
    spec = analytic.case_grid("spectral", 4)
    assert Options(pending=3).session_conf() == {poisson.PENDING: "3"}
    with pytest.raises(ValueError, match="maxReqsInFlight"):
        poisson.solve(analytic.scalar_field(spark, "spectral", spec), spec, options=Options("batched_async", pending=3))


def test_breakdown_times_every_pass(spark):
    spec = analytic.case_grid("unbounded", 6)
    cells = analytic.scalar_field(spark, "unbounded", spec)
    for strategy in STRATEGIES:
        t = metrics.breakdown(spark, lambda clock: poisson.solve(cells, spec, "gauss4", Options(strategy, workers=4, clock=clock)), strategy).collect()
        assert {(x.line_pass, x.phase) for x in t} == {(k, p) for k in range(1, 6) for p in metrics.PHASES} and all(x.seconds > 0 for x in t)


def test_asof_by_hours_equals_a_plain_search(spark):
    from spectral_spark import queries

    op_join_asof_time = queries.QUERIES["op_join_asof_time"]

    sf = "/root/testdata/sf0.001"
    events = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts", "event_id").collect()
    got = {(x.event_type, x.hour): x.value for x in op_join_asof_time(spark, sf).collect()}
    start = np.datetime64("2024-01-01")
    for t in {e.event_type for e in events}:
        mine = [(np.datetime64(e.ts), e.value) for e in events if e.event_type == t]
        for h in range(1, 720):
            last = [v for at, v in mine if at <= start + np.timedelta64(h, "h")]
            assert got[t, h] == (round(last[-1], 4) if last else None)


def test_measures(spark):
    a = spark.createDataFrame([(0, 0, 0, 1.0), (0, 0, 1, 2.0)], "ix int, iy int, iz int, v double")
    b = spark.createDataFrame([(0, 0, 0, 1.5)], "ix int, iy int, iz int, v double")
    assert metrics.e_inf(a, b).first().e_inf == 2.0
    t = spark.createDataFrame([("m", 1, 10.0), ("m", 2, 6.0)], "method string, nodes int, seconds double")
    s = {x.nodes: x for x in metrics.speedup(t, ["method"]).collect()}
    assert s[2].speedup == pytest.approx(10 / 6) and s[2].strong_efficiency == pytest.approx(10 / 12)
    w = metrics.weak_efficiency(t, ["method"])
    assert metrics.fit_beta(w, ["method"]).first().beta == pytest.approx(6 / 10 - 1)
    r = spark.range(1).select(metrics.throughput(F.lit(96.0**3), F.lit(1.0278), 14 / 3).alias("a"), metrics.throughput(F.lit(256.0**3), F.lit(3.704094056)).alias("b")).first()
    assert r.a == pytest.approx(32.14, abs=5e-3) and r.b == pytest.approx(36.23, abs=5e-3)
    rows = metrics.phases(spark, lambda: poisson.solve(a, GridSpec.of(*[Axis(4, layout=CELL)] * 3), "gauss2"), "packed_barrier", 4)
    assert rows[-1]["phase"] == "total" and len(rows) > 3


def test_plans_prune_and_place(spark):
    """Scans read the columns they need and push filters; a switch needs one exchange."""
    from spectral_spark.sources.fields import cube_lineitem

    cells = cube_lineitem(spark, "/root/testdata/sf0.001")
    plan = cells._jdf.queryExecution().executedPlan().toString()
    scan = next(x for x in plan.splitlines() if "ReadSchema" in x)
    assert "l_comment" not in scan and "l_returnflag" not in scan and "PushedFilters: [IsNotNull(l_shipdate)]" in scan
    u = poisson.solve(cells, GridSpec.of(*[Axis(8, layout=CELL)] * 3), "gauss4")
    # one for the cells of the table; five switches, or four of slabs, that place workers by number and sort nothing
    plan = u._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "FlatMapGroups" not in plan
    assert plan.count("Exchange ") - 1 in (3, 5) and (plan.count("Sort ") == 0)
    for strategy in STRATEGIES:
        u = poisson.solve(cells, GridSpec.of(*[Axis(8, layout=CELL)] * 3), "gauss4", Options(strategy, workers=4))
        plan = u._jdf.queryExecution().executedPlan().toString()
        assert plan.count("Exchange ") == 6 and "FlatMapGroups" not in plan


def test_stored_spectrum(spark, tmp_path):
    spec = analytic.case_grid("semi", 6)
    _, f = analytic.scalar_arrays("semi", spec)
    cells = analytic.scalar_field(spark, "semi", spec)
    want = monolithic_solve(f, spec, "gauss6")
    for decomposition in ("pencil", "slab"):
        for strategy in STRATEGIES:
            o = Options(strategy, decomposition, 6 if decomposition == "pencil" else 3)
            path = poisson.store_spectrum(spark, spec, "gauss6", str(tmp_path), o)
            assert poisson.store_spectrum(spark, spec, "gauss6", str(tmp_path), o) == path
            assert np.array_equal(as_array(poisson.solve(cells, spec, "gauss6", o, stored=path), spec.shape)[0], want)


def test_truncated_plane_kernel_is_limited():
    """With two open axes the broken-off sum limits the order; the quadrature does not."""
    e = {}
    for kernel in ("cutoff", kernels.TRUNCATED):
        for n in (32, 64):
            specs = analytic.tube_grids(n, 1)
            f, u = analytic.tube_arrays(specs[0])
            e[kernel, n] = np.abs(monolithic_curl_solve(f, specs, kernel) - u).max()
    assert e["cutoff", 64] < 1e-13 and e[kernels.TRUNCATED, 64] > 1e-5
    assert 0.5 < np.log2(e[kernels.TRUNCATED, 32] / e[kernels.TRUNCATED, 64]) < 2.5


def test_node_first_order_changes_no_result(spark):
    spec = analytic.case_grid("spectral", 6)
    w = Workers(build(spec), 6, node_size=2)
    assert w.peers(0, 1, 2)[:2] == [1, 0] and sorted(w.peers(0, 1, 2)) == [0, 1, 2]
    cells = analytic.scalar_field(spark, "spectral", spec)
    a, b = (as_array(poisson.solve(cells, spec, "gauss4", Options(workers=6, node_size=n)), spec.shape) for n in (0, 2))
    assert np.array_equal(a, b)


def test_automatic_choices(spark):
    from spectral_spark.plans.planner import auto_decomposition, auto_workers

    big = GridSpec.of(*[Axis(2048, UNBOUNDED, UNBOUNDED)] * 3)
    # the first axis has half a spectrum, 2049 slots, the others 4096
    assert auto_workers(big) == -(-16 * 2049 * 4096 * 4096 // (256 << 20)) and auto_decomposition(big, auto_workers(big)) == "slab"
    assert auto_decomposition(big, 5000) == "pencil"
    spec = analytic.case_grid("unbounded", 6)
    _, f = analytic.scalar_arrays("unbounded", spec)
    got = as_array(poisson.solve(analytic.scalar_field(spark, "unbounded", spec), spec, "gauss4", Options(decomposition="auto", workers=0)), spec.shape)[0]
    assert np.array_equal(got, monolithic_solve(f, spec, "gauss4"))


def test_aligned_solves_give_tiles(spark):
    for case, kernel in (("semi", "gauss6"), ("spectral", None)):
        spec = analytic.case_grid(case, 6)
        _, f = analytic.scalar_arrays(case, spec)
        want = monolithic_solve(f, spec, kernel) if kernel else f
        make = lambda ranges, f=f: f[tuple(slice(*r) for r in ranges)]
        for strategy in STRATEGIES:
            for decomposition in ("pencil", "slab"):
                got = np.full(spec.shape, np.nan)
                for t in poisson.solve_aligned(spark, spec, make, kernel, Options(strategy, decomposition, 6)).collect():
                    got[tuple(slice(a, a + n) for a, n in zip(t.o, t.n))] = np.frombuffer(t.re).reshape(t.n)
                assert np.allclose(got, want, rtol=1e-12, atol=1e-10), (case, strategy, decomposition)


LINES = "l_orderkey long, l_partkey long, l_suppkey long, l_quantity double, l_extendedprice double, l_discount double, l_returnflag string, l_shipdate timestamp"


def line_items(spark, folder, rows):
    """A folder whose line items have these order, part and supplier numbers, quantity, flag and days since 1995."""
    first = datetime(1995, 1, 1)
    rows = [(o, p, s, q, 1000.0, 0.0, flag, None if d is None else first + timedelta(days=d)) for o, p, s, q, flag, d in rows]
    spark.createDataFrame(rows, LINES).write.parquet(f"{folder}/lineitem.parquet")
    return str(folder)


def test_beta_is_fitted_to_the_line_items(spark, tmp_path):
    from spectral_spark.queries import QUERIES
    from spectral_spark.workloads.published import NODES, WEAK, measured

    # worker w of flag A has a load of 10 + w, flag R is even, N has one worker; null keys and quantities count nowhere
    rows = [(w + 384 * k, 0, 0, (10.0 + w) / 2, "A", 0) for w in range(384) for k in range(2)] + [(w, 0, 0, 5.0, "R", 0) for w in range(384)]
    rows += [(383, 0, 0, 1.0, "N", 0), (None, 0, 0, 1e6, "A", 0), (0, 0, 0, None, "A", 0)]
    got = {x.method: x.beta for x in QUERIES["beta_fit_published"](spark, line_items(spark, tmp_path, rows)).collect()}
    x, y = np.array(NODES) - 1, (9 + np.array(NODES)) / 10 - 1
    assert got == {"A": round(float((x * y).sum() / (x * x).sum()), 6), "R": 0.0, "N": None}
    published = {m.method: m.beta for m in metrics.fit_beta(metrics.weak_efficiency(measured(spark, WEAK), ["method"]), ["method"]).collect()}
    for method, seconds in WEAK.items():
        y = np.array(seconds) / seconds[0] - 1
        assert published[method] == pytest.approx((x * y).sum() / (x * x).sum())


def test_blocks_hold_the_line_items(spark, tmp_path):
    from spectral_spark.queries import QUERIES
    from spectral_spark.workloads.distribution import cube

    rows = [(0, p, s, 1.0, "A", d) for p, s, d in ((0, 0, 0), (33, 32, 32), (32, 31, 31), (16, 0, 0), (17, 0, 0), (40, 70, -1))]
    rows += [(0, None, 0, 1.0, "A", 0), (0, 0, 0, 1.0, "A", None)]
    got = QUERIES["block_table_32"](spark, line_items(spark, tmp_path, rows)).toPandas()
    assert len(got) == 12 and got.bytes.sum() == 8 * 33 * 32 * 32 and got.line_items.sum() == 6 and got.held.sum() == 5
    first = got[(got.o0 == 0) & (got.o1 == 0) & (got.o2 == 0)].iloc[0]
    assert (first.held, first.line_items) == (1, 2) and first.n0 == 16
    assert sorted(got[got.o0 == 16].line_items) == [0, 0, 0, 0, 1, 2]
    plain = block_table(spark, Workers(build(cube()), 6), 0, 1).toPandas().sort_values(["src", "dst"]).reset_index(drop=True)
    assert plain.equals(got.sort_values(["src", "dst"]).reset_index(drop=True)[list(plain.columns)])


def test_orders_choose_their_transform(spark, tmp_path):
    from spectral_spark.queries import QUERIES

    rows = [(2, 0), (4, 10), (3, 1), (5, -9), (7, 4), (None, 0), (2, None)]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long").write.parquet(str(tmp_path / "orders.parquet"))
    got = QUERIES["boundary_transform_table"](spark, str(tmp_path)).collect()
    assert len(got) == 2 * len(PAIRS) and sum(x.orders for x in got) == 5
    chosen = {(x.layout, x.left, x.right): (x.transform, x.kind, x.orders) for x in got if x.orders}
    for layout, pair, n in ((CELL, PAIRS[0], 2), (NODE, PAIRS[1], 2), (NODE, PAIRS[4], 1)):
        assert chosen[(layout, *pair)] == (*LineTransform(Axis(8, *pair, layout)).kind, n)


def test_sweep_solves_the_line_items(spark, tmp_path, monkeypatch):
    from spectral_spark.queries import QUERIES
    from spectral_spark.workloads import solves

    seen, cases = [], solves.sweep_cases()
    cases = [next(c for c in cases if c[2] == layout and c[0]) for layout in (CELL, NODE)]
    monkeypatch.setattr(solves, "sweep_cases", lambda: [(i, *c[1:]) for i, c in enumerate(cases)])
    monkeypatch.setattr(solves, "monolithic_solve", lambda f, *rest: seen.append(f) or monolithic_solve(f, *rest))
    rows = [(0, i, 3 * i, 1.0, "A", 5 * i) for i in range(200)] + [(0, None, 0, 1.0, "A", 0), (0, 0, 0, 1.0, "A", None)]
    got = QUERIES["combination_sweep"](spark, line_items(spark, tmp_path, rows)).collect()
    assert [x.difference for x in got] == [0.0, 0.0]
    for case, n in ((0, 8), (1, 9)):
        want = np.zeros((n, n, n))
        for i in range(200):
            want[i % n, 3 * i % n, 5 * i % n] += 1
        want = (want - want.mean()) / want.std()
        assert np.allclose(seen[case], np.roll(want, case, 0))


def test_examples_hold_the_line_items(spark, tmp_path):
    from spectral_spark.queries import QUERIES

    rows = [(o, 0, 0, 1.0, "A", 0) for o in (0, 32, 4, 5, 27, 28, 31, -1, None)]
    got = QUERIES["distribution_examples"](spark, line_items(spark, tmp_path, rows)).collect()
    by = {(x.p, x.worker): (x.n, x.held, x.line_items) for x in got}
    assert [by[7, w] for w in range(7)] == [(5, 2, 3), (5, 1, 1), (5, 0, 0), (5, 0, 0), (4, 0, 0), (4, 1, 1), (4, 2, 3)]
    assert [by[6, w][0] for w in range(6)] == [5, 5, 6, 5, 5, 6] and sum(by[6, w][2] for w in range(6)) == 8


def test_curves_follow_the_fullest_supplier(spark, tmp_path):
    from spectral_spark.queries import QUERIES
    from spectral_spark.workloads.published import NODES

    rows = [(0, 0, s, 1.0, "A", 0) for s in range(200)] + [(0, 0, 0, 1.0, "A", 0)] * 55 + [(0, 0, 7, 3.0, "N", 0)]
    rows += [(0, 0, None, 1e6, "A", 0), (0, 0, 0, None, "A", 0), (0, 0, 1, None, "R", 0)]
    got = {(x.method, x.r): (x.beta, x.speedup, x.efficiency) for x in QUERIES["ideal_scaling_curves"](spark, line_items(spark, tmp_path, rows)).collect()}
    assert len(got) == 2 * len(NODES)
    for method, b in (("A", 56 / 255), ("N", 1.0)):
        for n in NODES:
            assert got[method, n] == pytest.approx((b, 1 / ((1 - b) / n + b), 1 / (1 - b + n * b)), abs=6e-7)


@pytest.mark.parametrize("kernel", ["cutoff", "gauss10", "gauss2", "gauss4", "gauss6"])
def test_kernel_is_applied_to_the_line_items(spark, tmp_path, kernel):
    from spectral_spark.queries import QUERIES
    from spectral_spark.workloads.solves import spectral_grid

    rows = [(0, p, s, q, "A", d) for p, s, q, d in ((0, 0, 2e3, 0), (9, 8, 1e3, 5), (1, 2, 5e3, 3), (-1, 7, 7e3, -1), (2, 3, None, 1))]
    rows += [(0, None, 0, 1e6, "A", 0), (0, 0, None, 1e6, "A", 0), (0, 0, 0, 1e6, "A", None)]
    got = {(x.kx, x.ky, x.kz): (x.g, x.v) for x in QUERIES[f"kernel_table_{kernel}"](spark, line_items(spark, tmp_path, rows)).collect()}
    g = {(x.kx, x.ky, x.kz): x.re for x in poisson.spectrum(spark, spectral_grid(), kernel).collect()}
    held = {(0, 0, 0): 3, (1, 2, 3): 5, (8, 7, 4): 7}
    assert len(got) == 9 * 8 * 5 and got == {k: (round(x, 6) + 0.0, round(x * held.get(k, 0), 6) + 0.0) for k, x in g.items()}
