"""Operators around the solver: scans, joins, aggregates, windows, sets, functions, sources and sinks."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import transforms as T
from ..functions.sqlfuncs import register
from ..functions.transforms_sql import dense as dense_sql
from ..operators import poisson
from ..plans.distribution import Distribution
from ..plans.grid import CELL, PERIODIC, Axis, GridSpec
from ..queries import query, rounded
from ..sources.fields import GridSource, check_field_schema, components_lineitem, cube_events, cube_lineitem, cube_orders, dense, lines, table, write_slabs
from ..streaming.fields import shared_dir
from .distribution import _sql_owner
from .solves import C1, C2, C3, GRID, N, spectral_grid
from .transforms import HOURS, POINTS, POWER, hourly, power

C1R = f"SELECT CAST(ix AS INT) AS ix, CAST(iy AS INT) AS iy, CAST(iz AS INT) AS iz, v FROM ({C1}) c1"


def cells_of(df, *names):
    return df.select(*names, "ix", "iy", "iz", rounded("v").alias("v"))


# scans, sources, sinks


@query("op_scan_parquet_prune", "SELECT l_orderkey, l_linenumber, round(l_extendedprice, 4) + 0.0 AS price FROM lineitem WHERE l_quantity > 45 AND l_shipdate >= TIMESTAMP '2000-01-01'")
def op_scan_parquet_prune(spark, sf_dir):
    t = table(spark, sf_dir, "lineitem").where((F.col("l_quantity") > 45) & (F.col("l_shipdate") >= F.lit("2000-01-01").cast("timestamp")))
    return t.select("l_orderkey", "l_linenumber", rounded("l_extendedprice", 4).alias("price"))


@query("op_sink_roundtrip_slab", f"SELECT ix, iy, iz, round(v, 6) + 0.0 AS v FROM ({C1R}) c WHERE ix BETWEEN 2 AND 3")
def op_sink_roundtrip_slab(spark, sf_dir):
    """Written by slab; the sub-box reads its partition only."""
    path = shared_dir(spark)
    write_slabs(cube_lineitem(spark, sf_dir), path, 2)
    return cells_of(spark.read.parquet(path).where("slab = 1"))


def _bump_sql(t: str) -> tuple[str, str]:
    q = f"(1 - ({t}) * ({t}))"
    b = f"CASE WHEN abs({t}) < 1 THEN exp(10 * (1 - 1 / {q})) ELSE 0.0 END"
    d = f"CASE WHEN abs({t}) < 1 THEN 4 * exp(10 * (1 - 1 / {q})) * (10 * (-2 / pow({q}, 2) - 8 * pow({t}, 2) / pow({q}, 3)) + pow(20 * ({t}) / pow({q}, 2), 2)) ELSE 0.0 END"
    return b, d


def _grid_sql() -> str:
    lines_ = []
    for a, parts in (("x", ((1.4, "+"), (2.6, "+"))), ("y", ((1.0, "+"),)), ("z", ((0.6, "+"), (-0.6, "-")))):
        b, d = ("".join(f" {s} ({_bump_sql(f'i / 4.0 - ({c})')[k]})" for c, s in parts) for k in (0, 1))
        lines_.append(f"{a} AS (SELECT CAST(range AS INT) AS i, {b} AS b, {d} AS d FROM (SELECT CAST(range AS DOUBLE) AS i, range FROM range(0, 9)) r)")
    return f"WITH {', '.join(lines_)} SELECT x.i AS ix, y.i AS iy, z.i AS iz, round(x.d * y.b * z.b + x.b * y.d * z.b + x.b * y.b * z.d, 6) + 0.0 AS v FROM x CROSS JOIN y CROSS JOIN z"


@query("op_source_grid", _grid_sql())
def op_source_grid(spark, sf_dir):
    spark.dataSource.register(GridSource)
    return cells_of(spark.read.format("grid").option("case", "semi").option("n", 8).load())


@query("op_source_csv_json", f"SELECT ix, iy, iz, round(v, 6) + 0.0 AS v FROM ({C1R}) c")
def op_source_csv_json(spark, sf_dir):
    """Cells through JSON and CSV with a declared schema."""
    path, schema = shared_dir(spark), "ix int, iy int, iz int, v double"
    cube_lineitem(spark, sf_dir).write.json(f"{path}/json")
    spark.read.schema(schema).json(f"{path}/json").write.csv(f"{path}/csv")
    return cells_of(check_field_schema(spark.read.schema(schema).csv(f"{path}/csv")))


# filters and projections


@query("op_filter_box", f"SELECT ix, iy, iz, round(v, 6) + 0.0 AS v FROM ({C1R}) c WHERE ix BETWEEN 1 AND 4 AND iy BETWEEN 2 AND 5 AND iz < 6")
def op_filter_box(spark, sf_dir):
    return cells_of(cube_lineitem(spark, sf_dir).where("ix between 1 and 4 and iy between 2 and 5 and iz < 6"))


_LOW = f"WITH e AS ({POINTS}), f AS (SELECT key, k, sum(v * cos(2 * pi() * k * j / 64)) AS re, -sum(v * sin(2 * pi() * k * j / 64)) AS im FROM e CROSS JOIN (SELECT range AS k FROM range(0, 9)) m WHERE j < 64 GROUP BY key, k) SELECT key, CAST(j AS INT) AS j, round(sum((re * cos(2 * pi() * k * j / 64) - im * sin(2 * pi() * k * j / 64)) * CASE WHEN k = 0 THEN 1 ELSE 2 END) / 64, 6) + 0.0 AS v FROM f CROSS JOIN (SELECT range AS j FROM range(0, 64)) p GROUP BY key, j"


@query("op_filter_lowpass", _LOW)
def op_filter_lowpass(spark, sf_dir):
    """Modes up to 8 of each embedding, and back."""
    y = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), T.dft_r2c_column()(T.as_doubles(F.col("embedding"))).alias("y"))
    low = lambda c: F.transform(c, lambda v, k: F.when(k <= 8, v).otherwise(0.0))
    return y.select("key", F.posexplode(T.dft_c2r_column(64)(low(F.col("y.re")), low(F.col("y.im")))).alias("j", "v")).select("key", "j", rounded("v").alias("v"))


@query("op_project_index", f"SELECT o_orderkey, {_sql_owner('strided', '(o_orderkey % 1000)', 1000, 48)} AS worker, CAST(o_orderkey // 7 AS BIGINT) AS bin, CAST(o_custkey % 64 AS INT) AS slot FROM orders")
def op_project_index(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    return o.select("o_orderkey", Distribution(1000, 48).owner(F.col("o_orderkey") % 1000).alias("worker"), F.expr("o_orderkey div 7").alias("bin"), F.pmod("o_custkey", F.lit(64)).cast("int").alias("slot"))


# joins

_MODE_SQL = f"SELECT c.ix, c.iy, c.iz, round(c.v * CASE WHEN k2 > 0 THEN -1.0 / k2 ELSE 0.0 END, 6) + 0.0 AS v FROM ({C1R}) c JOIN (SELECT px, py, pz, (pi() * px) * (pi() * px) + (pi() * (py + 0.5)) * (pi() * (py + 0.5)) + (2 * pi() * pz) * (2 * pi() * pz) AS k2 FROM {GRID} g WHERE pz <= 4) k ON px = ix AND py = iy AND pz = iz"


def _mode_join(hint: str):
    def run(spark, sf_dir):
        """The cube, taken as a spectrum, times the kernel of its modes."""
        g = poisson.spectrum(spark, spectral_grid(), "singular").select(F.col("kx").alias("ix"), F.col("ky").alias("iy"), F.col("kz").alias("iz"), "re")
        out = cube_lineitem(spark, sf_dir).hint(hint).join(g, ["ix", "iy", "iz"])
        return out.select("ix", "iy", "iz", rounded(F.col("v") * F.col("re")).alias("v"))

    return run


query("op_join_hash_modes", _MODE_SQL)(_mode_join("shuffle_hash"))
query("op_join_merge_modes", _MODE_SQL)(_mode_join("merge"))


@query("op_join_broadcast_radial", f"SELECT CAST(ix AS INT) AS ix, CAST(iy AS INT) AS iy, CAST(iz AS INT) AS iz, round(v * sqrt(ix * ix + iy * iy + iz * iz), 6) + 0.0 AS v FROM ({C2}) c")
def op_join_broadcast_radial(spark, sf_dir):
    """A radial factor by squared distance: 3 * 49 + 1 rows at most, so its table is broadcast."""
    radial = spark.range(3 * (N - 1) ** 2 + 1).select(F.col("id").alias("n2"), F.sqrt("id").alias("g"))
    c = cube_events(spark, sf_dir).withColumn("n2", (F.col("ix") ** 2 + F.col("iy") ** 2 + F.col("iz") ** 2).cast("long"))
    return c.join(F.broadcast(radial), "n2").select("ix", "iy", "iz", rounded(F.col("v") * F.col("g")).alias("v"))


_L48 = f"SELECT key, j // 15 AS j, sum(v) AS v FROM ({HOURS}) h GROUP BY 1, 2"


@query("op_join_nested_direct", f"WITH l AS ({_L48}) SELECT a.key AS event_type, CAST(a.j AS INT) AS j, round(sum(abs(a.j - b.j) / 2.0 * b.v), 6) + 0.0 AS u FROM l a JOIN l b ON a.key = b.key GROUP BY 1, 2")
def op_join_nested_direct(spark, sf_dir):
    """Pairwise sum over 48 bins of each event type."""
    b = hourly(spark, sf_dir).groupBy("event_type", F.expr("j div 15").alias("j")).agg(F.sum("v").alias("v"))
    a = b.select("event_type", F.col("j").alias("i"))
    return a.join(b, "event_type").groupBy("event_type", F.col("i").cast("int").alias("j")).agg(rounded(F.sum(F.abs(F.col("i") - F.col("j")) / 2.0 * F.col("v"))).alias("u"))


@query("op_join_range_owner", "SELECT doc_id, CAST(max(r) AS INT) AS worker FROM documents CROSS JOIN (SELECT range AS r FROM range(0, 48)) w WHERE (r * 500) // 48 <= doc_id % 500 GROUP BY doc_id")
def op_join_range_owner(spark, sf_dir):
    """Index to worker by start and end, for a distribution without a closed owner."""
    w = Distribution(500, 48, "proportional").table(spark)
    d = table(spark, sf_dir, "documents").select("doc_id", (F.col("doc_id") % 500).alias("i"))
    return d.join(F.broadcast(w), (F.col("i") >= F.col("first")) & (F.col("i") < F.col("after"))).select("doc_id", "worker")


@query("op_join_overlap_blocks", "WITH a AS (SELECT range AS w, (range * 100) // 7 AS lo, ((range + 1) * 100) // 7 AS hi FROM range(0, 7)), b AS (SELECT range AS w, (range * 100) // 6 AS lo, ((range + 1) * 100) // 6 AS hi FROM range(0, 6)) SELECT CAST(a.w AS INT) AS src, CAST(b.w AS INT) AS dst, CAST(greatest(a.lo, b.lo) AS BIGINT) AS lo, CAST(least(a.hi, b.hi) AS BIGINT) AS hi FROM a JOIN b ON a.lo < b.hi AND b.lo < a.hi")
def op_join_overlap_blocks(spark, sf_dir):
    a, b = (Distribution(100, p, "proportional").table(spark) for p in (7, 6))
    a, b = a.select(F.col("worker").alias("src"), F.col("first").alias("alo"), F.col("after").alias("ahi")), b.select(F.col("worker").alias("dst"), F.col("first").alias("blo"), F.col("after").alias("bhi"))
    return a.join(b, (F.col("alo") < F.col("bhi")) & (F.col("blo") < F.col("ahi"))).select("src", "dst", F.greatest("alo", "blo").alias("lo"), F.least("ahi", "bhi").alias("hi"))


@query("op_join_asof_time", "SELECT t AS event_type, CAST(h AS INT) AS hour, round((SELECT value FROM events e WHERE e.event_type = t AND ts <= TIMESTAMP '2024-01-01' + to_hours(CAST(h AS INT)) ORDER BY ts DESC, event_id DESC LIMIT 1), 4) + 0.0 AS value FROM (SELECT DISTINCT event_type AS t FROM events) a CROSS JOIN (SELECT range AS h FROM range(1, 720)) b")
def op_join_asof_time(spark, sf_dir):
    """The last event at or before each hour node: the last one of every hour first, then carried forward; no sort of events."""
    e = table(spark, sf_dir, "events").where("ts is not null")
    # an event at the very node belongs to it, any later one to the next
    second = F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lit("2024-01-01").cast("timestamp"))
    node = F.greatest(F.ceil(second / F.lit(3_600_000_000)), F.lit(1)).cast("int")
    last = e.groupBy("event_type", node.alias("hour")).agg(F.max_by("value", F.struct("ts", "event_id")).alias("value"))
    # five event types by 719 nodes
    nodes = e.select("event_type").distinct().crossJoin(spark.range(1, 720).select(F.col("id").cast("int").alias("hour")))
    w = Window.partitionBy("event_type").orderBy("hour").rowsBetween(Window.unboundedPreceding, 0)
    out = nodes.join(last, ["event_type", "hour"], "left").withColumn("last", F.last("value", ignorenulls=True).over(w))
    return out.select("event_type", "hour", rounded("last", 4).alias("value"))


@query("op_join_left_dense", f"SELECT CAST(px AS INT) AS ix, CAST(py AS INT) AS iy, CAST(pz AS INT) AS iz, round(coalesce(v, 0.0), 6) + 0.0 AS v FROM {GRID} g LEFT JOIN ({C3}) c ON px = ix AND py = iy AND pz = iz")
def op_join_left_dense(spark, sf_dir):
    return cells_of(dense(spark, cube_orders(spark, sf_dir), N))


@query("op_join_full_compare", f"SELECT count(*) AS cells, 0.0 + round(0.0, 6) AS difference FROM {GRID} g")
def op_join_full_compare(spark, sf_dir):
    """Full outer comparison of two exchange strategies."""
    f, spec = cube_lineitem(spark, sf_dir), spectral_grid()
    a, b = (poisson.solve(f, spec, "gauss4", poisson.Options(s)).select("ix", "iy", "iz", F.col("v").alias(c)) for s, c in (("packed_barrier", "a"), ("unpacked_direct", "b")))
    return a.join(b, ["ix", "iy", "iz"], "full").agg(F.count("*").alias("cells"), rounded(F.max(F.abs(F.coalesce("a", F.lit(1e9)) - F.coalesce("b", F.lit(-1e9))))).alias("difference"))


@query("op_join_semi_labels", "SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def op_join_semi_labels(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "n_chars").join(table(spark, sf_dir, "labels").where("quality = 1"), "doc_id", "left_semi")


@query("op_join_anti_labels", "SELECT doc_id, n_chars FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti_labels(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "n_chars").join(table(spark, sf_dir, "labels"), "doc_id", "left_anti")


# aggregates


@query("op_agg_rasterise", f"SELECT ix, iy, iz, round(v, 6) + 0.0 AS v FROM ({C1R}) c")
def op_agg_rasterise(spark, sf_dir):
    return cells_of(cube_lineitem(spark, sf_dir))


@query("op_agg_pencil_collect", f"SELECT CAST(px AS INT) AS ix, CAST(py AS INT) AS iy, round(list_sum(list_transform(list(coalesce(v, 0.0) * (pz + 1)), lambda x: x)), 6) + 0.0 AS weighted FROM {GRID} g LEFT JOIN ({C1}) c ON px = ix AND py = iy AND pz = iz GROUP BY 1, 2")
def op_agg_pencil_collect(spark, sf_dir):
    """Lines as sorted arrays; a weighted sum over each shows the order."""
    p = dense(spark, cube_lineitem(spark, sf_dir), N).groupBy("ix", "iy").agg(F.array_sort(F.collect_list(F.struct("iz", "v"))).alias("line"))
    return p.select("ix", "iy", rounded(F.aggregate(F.transform("line", lambda s, i: s["v"] * (i + 1)), F.lit(0.0), lambda a, b: a + b)).alias("weighted"))


@query("op_agg_distinct_radial", "SELECT CAST(x.range * x.range + y.range * y.range + z.range * z.range AS BIGINT) AS n2, count(*) AS points FROM range(0, 16) x CROSS JOIN range(0, 16) y CROSS JOIN range(0, 16) z GROUP BY 1")
def op_agg_distinct_radial(spark, sf_dir):
    i = F.col("id")
    x, y, z = F.floor(i / 256), F.floor(i / 16) % 16, i % 16
    return spark.range(16**3).groupBy((x * x + y * y + z * z).cast("long").alias("n2")).agg(F.count("*").alias("points"))


@query("op_agg_norms", f"SELECT round(sum(abs(v)), 4) + 0.0 AS l1, round(sqrt(sum(v * v)), 4) + 0.0 AS l2, round(max(abs(v)), 4) + 0.0 AS linf FROM ({C1R}) c")
def op_agg_norms(spark, sf_dir):
    v = F.col("v")
    return cube_lineitem(spark, sf_dir).agg(rounded(F.sum(F.abs(v)), 4).alias("l1"), rounded(F.sqrt(F.sum(v * v)), 4).alias("l2"), rounded(F.max(F.abs(v)), 4).alias("linf"))


def _marginals(kind: str, sql: str):
    def run(spark, sf_dir):
        c = cube_lineitem(spark, sf_dir)
        if kind == "sets":
            c.createOrReplaceTempView(name := f"c1_{uuid.uuid4().hex}")
            out = spark.sql(f"SELECT ix, iy, sum(v) AS v FROM {name} GROUP BY GROUPING SETS ((ix), (iy), ())")
        else:
            out = getattr(c, kind)("ix", "iy").agg(F.sum("v").alias("v"))
        return out.select("ix", "iy", rounded("v").alias("v"))

    query({"sets": "op_agg_grouping_sets"}.get(kind, f"op_agg_{kind}"), f"SELECT ix, iy, round(sum(v), 6) + 0.0 AS v FROM ({C1R}) c GROUP BY {sql}")(run)


_marginals("sets", "GROUPING SETS ((ix), (iy), ())")
_marginals("cube", "CUBE (ix, iy)")
_marginals("rollup", "ROLLUP (ix, iy)")


@query("field_rollup_lineitem", "SELECT r_name, n_name, round(sum(l_extendedprice * (1 - l_discount)) / 1e6, 6) + 0.0 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def field_rollup_lineitem(spark, sf_dir):
    t = lambda n: table(spark, sf_dir, n)
    li = t("lineitem").select("l_orderkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))
    j = li.join(t("orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    # nations and regions are dictionaries of fixed size
    j = j.join(F.broadcast(t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.rollup("r_name", "n_name").agg(rounded(F.sum("v") / 1e6).alias("v"))


@query("op_agg_approx", "SELECT event_type, count(DISTINCT user_id) AS users, true AS users_near, true AS median_near FROM events GROUP BY event_type")
def op_agg_approx(spark, sf_dir):
    """Approximate distinct users and median of each event type, held against the exact ones: within 15 % and 2 % of the ranks."""
    e = table(spark, sf_dir, "events")
    rough = e.groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("a"), F.percentile_approx("value", 0.5).alias("m"))
    exact = e.groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))
    # five event types
    ranks = e.join(F.broadcast(rough), "event_type").groupBy("event_type", "a").agg(F.avg((F.col("value") <= F.col("m")).cast("double")).alias("rank"))
    near = (F.abs(F.col("a") - F.col("users")) <= 0.15 * F.col("users")).alias("users_near")
    return exact.join(ranks, "event_type").select("event_type", "users", near, (F.abs(F.col("rank") - 0.5) <= 0.02).alias("median_near"))


@query("op_agg_pivot_components", "SELECT CAST(ix AS INT) AS ix, round(sum(p * l_tax), 6) + 0.0 AS c0, round(sum(p * l_discount), 6) + 0.0 AS c1, round(sum(p), 6) + 0.0 AS c2 FROM (SELECT l_partkey % 8 AS ix, l_extendedprice / 1e6 AS p, l_tax, l_discount FROM lineitem) l GROUP BY 1")
def op_agg_pivot_components(spark, sf_dir):
    p = components_lineitem(spark, sf_dir).groupBy("ix").pivot("comp", [0, 1, 2]).agg(F.sum("v"))
    return p.select("ix", *[rounded(F.col(str(c))).alias(f"c{c}") for c in range(3)])


# windows


@query("op_win_laplacian", f"SELECT ix, iy, iz, round(r - 2 * v + l, 6) + 0.0 AS v FROM (SELECT *, lag(v) OVER w AS l, lead(v) OVER w AS r FROM (SELECT CAST(px AS INT) AS ix, CAST(py AS INT) AS iy, CAST(pz AS INT) AS iz, coalesce(v, 0.0) AS v FROM {GRID} g LEFT JOIN ({C1}) c ON px = c.ix AND py = c.iy AND pz = c.iz) d WINDOW w AS (PARTITION BY iy, iz ORDER BY ix)) q WHERE l IS NOT NULL AND r IS NOT NULL")
def op_win_laplacian(spark, sf_dir):
    w = Window.partitionBy("iy", "iz").orderBy("ix")
    d = dense(spark, cube_lineitem(spark, sf_dir), N).withColumn("l", F.lag("v").over(w)).withColumn("r", F.lead("v").over(w))
    return d.where("l is not null and r is not null").select("ix", "iy", "iz", rounded(F.col("r") - 2 * F.col("v") + F.col("l")).alias("v"))


_RANKED = "SELECT event_type, CAST(k AS INT) AS k, CAST(rank() OVER w AS INT) AS r, CAST(dense_rank() OVER w AS INT) AS d, CAST(row_number() OVER w AS INT) AS n, CAST(ntile(4) OVER w AS INT) AS q"


@query("op_win_rank_modes", f"{_RANKED} FROM (SELECT event_type, k, round(power, 6) AS power FROM ({POWER}) p WHERE k >= 1) s WINDOW w AS (PARTITION BY event_type ORDER BY power DESC, k)")
def op_win_rank_modes(spark, sf_dir):
    w = Window.partitionBy("event_type").orderBy(F.desc("power"), "k")
    p = power(spark, sf_dir).where("k >= 1").withColumn("power", F.round("power", 6))
    return p.select("event_type", "k", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.row_number().over(w).alias("n"), F.ntile(4).over(w).alias("q"))


@query("op_win_cumulative_power", f"SELECT event_type, CAST(k AS INT) AS k, round(sum(power) OVER (PARTITION BY event_type ORDER BY k ROWS UNBOUNDED PRECEDING) / sum(power) OVER (PARTITION BY event_type), 6) + 0.0 AS share FROM ({POWER}) p WHERE k >= 1")
def op_win_cumulative_power(spark, sf_dir):
    w = Window.partitionBy("event_type")
    p = power(spark, sf_dir).where("k >= 1")
    share = F.sum("power").over(w.orderBy("k").rowsBetween(Window.unboundedPreceding, 0)) / F.sum("power").over(w)
    return p.select("event_type", "k", rounded(share).alias("share"))


@query("op_win_range_frame", f"SELECT key AS event_type, CAST(j AS INT) AS j, round(avg(v) OVER (PARTITION BY key ORDER BY j RANGE BETWEEN 3 PRECEDING AND 3 FOLLOWING), 6) + 0.0 AS v FROM ({HOURS}) h")
def op_win_range_frame(spark, sf_dir):
    w = Window.partitionBy("event_type").orderBy("j").rangeBetween(-3, 3)
    return hourly(spark, sf_dir).select("event_type", "j", rounded(F.avg("v").over(w)).alias("v"))


# top-k, sort, sets


@query("op_topk_modes", f"SELECT event_type, CAST(k AS INT) AS k, round(power, 6) + 0.0 AS power FROM ({POWER}) p WHERE k >= 1 ORDER BY power DESC, event_type, k LIMIT 10")
def op_topk_modes(spark, sf_dir):
    return power(spark, sf_dir).where("k >= 1").orderBy(F.desc("power"), "event_type", "k").limit(10).select("event_type", "k", rounded("power").alias("power"))


@query("op_topk_per_group", f"SELECT event_type, CAST(k AS INT) AS k, round(power, 6) + 0.0 AS power FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY power DESC, k) AS r FROM ({POWER}) p WHERE k >= 1) q WHERE r <= 3")
def op_topk_per_group(spark, sf_dir):
    w = Window.partitionBy("event_type").orderBy(F.desc("power"), "k")
    return power(spark, sf_dir).where("k >= 1").withColumn("r", F.row_number().over(w)).where("r <= 3").select("event_type", "k", rounded("power").alias("power"))


@query("op_sort_linear_index", f"SELECT CAST((ix * 8 + iy) * 8 + iz AS INT) AS i, round(v, 6) + 0.0 AS v FROM ({C1R}) c ORDER BY 1")
def op_sort_linear_index(spark, sf_dir):
    c = cube_lineitem(spark, sf_dir)
    return c.select(((F.col("ix") * N + F.col("iy")) * N + F.col("iz")).alias("i"), rounded("v").alias("v")).orderBy("i")


@query("op_set_union_components", "SELECT CAST(comp AS INT) AS comp, round(sum(v), 6) + 0.0 AS v FROM (SELECT 0 AS comp, l_extendedprice / 1e6 * l_tax AS v FROM lineitem UNION ALL SELECT 2, l_extendedprice / 1e6 FROM lineitem) u GROUP BY comp")
def op_set_union_components(spark, sf_dir):
    f = components_lineitem(spark, sf_dir)
    return f.where("comp = 0").unionByName(f.where("comp = 2")).groupBy("comp").agg(rounded(F.sum("v")).alias("v"))


@query("op_set_intersect_masks", "SELECT doc_id FROM documents WHERE n_chars > 1000 INTERSECT SELECT doc_id FROM labels WHERE toxic = 0")
def op_set_intersect_masks(spark, sf_dir):
    return table(spark, sf_dir, "documents").where("n_chars > 1000").select("doc_id").intersect(table(spark, sf_dir, "labels").where("toxic = 0").select("doc_id"))


@query("op_set_except_masks", "SELECT doc_id FROM documents WHERE n_chars > 1000 EXCEPT SELECT doc_id FROM labels WHERE toxic = 1")
def op_set_except_masks(spark, sf_dir):
    return table(spark, sf_dir, "documents").where("n_chars > 1000").select("doc_id").subtract(table(spark, sf_dir, "labels").where("toxic = 1").select("doc_id"))


@query("op_set_except_all", "SELECT CAST(0 AS BIGINT) AS only_first, CAST(0 AS BIGINT) AS only_second")
def op_set_except_all(spark, sf_dir):
    """Two strategies' outputs, each less the other: both empty."""
    f, spec = cube_lineitem(spark, sf_dir), spectral_grid()
    a, b = (poisson.solve(f, spec, "gauss4", poisson.Options(s)) for s in ("packed_barrier", "batched_async"))
    first = a.exceptAll(b).agg(F.count("*").alias("only_first"))
    # one row on each side
    return first.crossJoin(b.exceptAll(a).agg(F.count("*").alias("only_second")))


# functions


@query("op_fn_math", f"SELECT key, CAST(j AS INT) AS j, round(sin(v) + cos(v) * exp(-v * v) + ln(1 + abs(v)) + sqrt(abs(v)) + pow(v, 3) + floor(v) + sign(v), 6) + 0.0 AS y FROM ({POINTS}) p WHERE j < 64")
def op_fn_math(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), F.posexplode(T.as_doubles(F.col("embedding"))).alias("j", "v"))
    v = F.col("v")
    return e.select("key", "j", rounded(F.sin(v) + F.cos(v) * F.exp(-v * v) + F.log(1 + F.abs(v)) + F.sqrt(F.abs(v)) + F.pow(v, 3) + F.floor(v) + F.signum(v)).alias("y"))


@query("op_fn_date", "SELECT o_orderkey, date_trunc('month', o_orderdate) AS month, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INT) AS d, CAST(hour(o_orderdate + INTERVAL 30 HOUR) AS INT) AS h, epoch_us(o_orderdate) AS us FROM orders")
def op_fn_date(spark, sf_dir):
    o = table(spark, sf_dir, "orders").withColumn("o_orderdate", F.col("o_orderdate").cast("timestamp"))
    return o.select("o_orderkey", F.date_trunc("month", "o_orderdate").alias("month"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("d"), F.hour(F.col("o_orderdate") + F.expr("INTERVAL 30 HOURS")).alias("h"), F.unix_micros("o_orderdate").alias("us"))


@query("op_fn_string", "SELECT page_id, CAST(length(html) AS INT) AS n, CAST(len(string_split(regexp_extract(url, '://[^/]+(/[^?#]*)', 1), '/')) - 1 AS INT) AS depth, lower(substring(url, 1, 5)) AS scheme FROM pages")
def op_fn_string(spark, sf_dir):
    p = table(spark, sf_dir, "pages")
    return p.select("page_id", F.length("html").alias("n"), (F.size(F.split(F.regexp_extract("url", "://[^/]+(/[^?#]*)", 1), "/")) - 1).alias("depth"), F.lower(F.substring("url", 1, 5)).alias("scheme"))


@query("op_fn_array", f"SELECT key AS vec_id, round(sum(v * (j + 1)), 5) + 0.0 AS ramp, round(sum(v * v), 5) + 0.0 AS energy FROM ({POINTS}) p WHERE j < 64 GROUP BY key")
def op_fn_array(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("vec_id", T.as_doubles(F.col("embedding")).alias("x"))
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda a, b: a + b)
    ramp = total(F.zip_with("x", F.transform(F.sequence(F.lit(1), F.lit(64)), lambda i: i.cast("double")), lambda a, b: a * b))
    return e.select("vec_id", rounded(ramp, 5).alias("ramp"), rounded(total(F.transform("x", lambda v: v * v)), 5).alias("energy"))


@query("op_fn_map", f"SELECT event_type, CAST(k AS INT) AS k, round(power, 6) + 0.0 AS power FROM ({POWER}) p WHERE k >= 1 AND power > 1.0")
def op_fn_map(spark, sf_dir):
    """Mode to power as a map, filtered, and exploded again."""
    p = power(spark, sf_dir).where("k >= 1").groupBy("event_type").agg(F.map_from_entries(F.collect_list(F.struct("k", "power"))).alias("m"))
    return p.select("event_type", F.explode(F.map_filter("m", lambda k, v: v > 1.0)).alias("k", "power")).select("event_type", "k", rounded("power").alias("power"))


@query("op_fn_json", "SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1")
def op_fn_json(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n"))


@query("op_fn_decimal_cast", "SELECT l_returnflag, round(CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 4))) AS DOUBLE) / 1e6, 6) + 0.0 AS v FROM lineitem GROUP BY 1")
def op_fn_decimal_cast(spark, sf_dir):
    t = table(spark, sf_dir, "lineitem")
    return t.groupBy("l_returnflag").agg(rounded(F.sum(F.col("l_extendedprice").cast("decimal(18,4)")).cast("double") / 1e6).alias("v"))


_DCT2 = f"SELECT key AS vec_id, CAST(k AS INT) AS k, round(y, 6) + 0.0 AS y FROM ({dense_sql('dct2', f'({POINTS}) p', 64)}) q"


@query("op_udf_scalar_arrow", _DCT2)
def op_udf_scalar_arrow(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode(T.dct_column(2)(T.as_doubles(F.col("embedding")))).alias("k", "y"))
    return e.select("vec_id", "k", rounded("y").alias("y"))


@query("op_udaf_pencil", f"SELECT CAST(px AS INT) AS ix, CAST(py AS INT) AS iy, round(sum(coalesce(v, 0.0) * cos(pi() * (pz + 0.5) / 8)) * 2, 6) + 0.0 AS mode1 FROM {GRID} g LEFT JOIN ({C1}) c ON px = ix AND py = iy AND pz = iz GROUP BY 1, 2")
def op_udaf_pencil(spark, sf_dir):
    """A grouped function builds each line and transforms it."""

    def run(p: pd.DataFrame) -> pd.DataFrame:
        import numpy as np

        x = np.zeros(N)
        x[p.iz] = p.v
        return pd.DataFrame({"ix": [p.ix[0]], "iy": [p.iy[0]], "mode1": [T.dct(x, 2)[1]]})

    out = dense(spark, cube_lineitem(spark, sf_dir), N).groupBy("ix", "iy").applyInPandas(run, "ix int, iy int, mode1 double")
    return out.select("ix", "iy", rounded("mode1").alias("mode1"))


@query("op_udtf_grid", "SELECT CAST(x.range AS INT) AS ix, CAST(y.range AS INT) AS iy, CAST(z.range AS INT) AS iz FROM range(0, 4) x CROSS JOIN range(0, 3) y CROSS JOIN range(0, 2) z")
def op_udtf_grid(spark, sf_dir):
    register(spark)
    return spark.sql("SELECT * FROM grid_points(4, 3, 2)")


@query("op_udtf_modes", "SELECT CAST(range AS INT) AS k, round(pi() * (range + 1), 6) + 0.0 AS omega FROM range(0, 12)")
def op_udtf_modes(spark, sf_dir):
    register(spark)
    return spark.sql("SELECT k, round(omega, 6) + 0.0D AS omega FROM modes(12, 1)")


@query("op_sql_functions", _DCT2)
def op_sql_functions(spark, sf_dir):
    """The transform called from SQL."""
    register(spark)
    table(spark, sf_dir, "embeddings").select("vec_id", T.as_doubles(F.col("embedding")).alias("line")).createOrReplaceTempView(name := f"lines_{uuid.uuid4().hex}")
    return spark.sql(f"SELECT vec_id, k, round(y, 6) + 0.0D AS y FROM (SELECT vec_id, posexplode(dct(line, 2)) AS (k, y) FROM {name})")


@query("dense_sql_transform_spark", _DCT2)
def dense_sql_transform_spark(spark, sf_dir):
    """The dense definition itself, as SQL in Spark."""
    table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), F.posexplode(T.as_doubles(F.col("embedding"))).alias("j", "v")).createOrReplaceTempView(name := f"points_{uuid.uuid4().hex}")
    return spark.sql(dense_sql("dct2", name, 64, spark=True)).select(F.col("key").alias("vec_id"), F.col("k").cast("int").alias("k"), rounded("y").alias("y"))


__all__ = ["Axis", "CELL", "GridSpec", "PERIODIC", "lines"]
