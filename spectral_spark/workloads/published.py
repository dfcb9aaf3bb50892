"""Published timings replayed through the scaling measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import metrics
from ..queries import query, rounded
from ..sources.fields import table

# Seconds of a solve on 1, 2, 4, ... nodes of 128 cores, open boundaries.
NODES = (1, 2, 4, 8, 16, 32, 64, 128, 256, 384)
# 96^3 unknowns per core
WEAK = {
    "packed_barrier": (1.0887, 1.1064, 1.1884, 1.2140, 1.2242, 1.2673, 1.2731, 1.3578, 1.5682, 1.6957),
    "batched_async": (1.0278, 1.0473, 1.0757, 1.1161, 1.1299, 1.1699, 1.1314, 1.2433, 1.7098, 1.5925),
    "unpacked_direct": (0.8069, 0.8604, 0.9622, 1.0166, 1.0887, 1.2109, 1.2269, 1.3869, 1.6270, 2.2612),
}
# 1280^3 unknowns in all
STRONG = {
    "packed_barrier": (21.880, 10.814, 5.803, 2.863, 1.426, 0.728, 0.368, 0.217, 0.0993, 0.0839),
    "unpacked_direct": (16.700, 8.897, 4.766, 2.390, 1.279, 0.660, 0.338, 0.208, 0.124, 0.112),
    "batched_async": (20.387, 9.906, 5.105, 2.547, 1.288, 0.674, 0.311, 0.191, 0.115, 0.107),
}
# Seconds of a periodic forward and backward transform, 256^3 unknowns per core.
LIBRARY_NODES = (1, 2, 8, 32, 128)
LIBRARY = {
    "reference library": (3.704, 4.055, 4.390, 5.316, 7.251),
    "unpacked_direct": (3.715, 3.945, 4.660, 5.750, 7.208),
    "batched_async": (4.828, 4.954, 5.165, 5.095, 5.239),
}
# batched_async on three machines, 1 to 128 nodes
MACHINES = {
    "HDR100": (0.9765, 1.0446, 1.1528, 1.2952, 1.4661, 1.4765, 1.4307, 1.9306),
    "HDR200": (1.0278, 1.0473, 1.0757, 1.1161, 1.1299, 1.1699, 1.1314, 1.2433),
    "Slingshot": (0.9594, 0.9970, 1.1145, 1.1630, 1.1918, 1.2846, 1.3680, 1.5643),
}
# E_inf of the open case, 33 to 2049 points per axis
POINTS = (33, 65, 129, 257, 513, 1025, 2049)
ERRORS = {
    "singular": (0.0526328, 0.0132118, 0.00330628, 0.00082678, 0.000206708, 5.16778e-05, 1.29195e-05),
    "lattice": (0.0112963, 0.00280508, 0.000700092, 0.000174949, 4.37328e-05, 1.09329e-05, 2.73321e-06),
    "gauss2": (0.3437, 0.107774, 0.0286782, 0.00728505, 0.0018286, 0.00045761, 0.000114431),
    "gauss4": (0.0959881, 0.0087914, 0.000608172, 3.90018e-05, 2.4534e-06, 1.53585e-07, 9.60297e-09),
    "gauss6": (0.0232007, 0.00058816, 1.04068e-05, 1.6777e-07, 2.642e-09, 4.13618e-11, 6.47815e-13),
    "gauss8": (0.00485968, 3.23509e-05, 1.44436e-07, 5.87122e-10, 2.38487e-12, 1.12133e-14, 3.88578e-15),
    "gauss10": (0.000861695, 3.02079e-06, 8.32719e-09, 1.26446e-11, 1.39761e-14, 3.77476e-15, 3.88578e-15),
    "cutoff": (2.52418e-08, 9.65466e-13, 1.33227e-15, 2.55351e-15, 3.44169e-15, 3.77476e-15, 3.88578e-15),
}
# E_inf of the half-open case, 33 and 65 points per axis
SEMI = {
    "singular": (0.0516755, 0.0131966),
    "lattice": (0.0111028, 0.00280275),
    "gauss2": (0.337844, 0.107653),
    "gauss4": (0.0939906, 0.00877942),
    "gauss6": (0.0226599, 0.000587287),
    "gauss8": (0.00474199, 3.87118e-05),
    "gauss10": (0.000923655, 6.26398e-06),
    "cutoff": (3.81747e-08, 1.39833e-12),
}
# E_inf of the tube's velocity by derivative, 33 and 65 points per axis
TUBE = {
    "spectral": {
        "singular": (0.0256073, 0.00722996),
        "gauss2": (0.711435, 0.287455),
        "gauss4": (0.362443, 0.0677251),
        "gauss6": (0.182082, 0.016062),
        "gauss8": (0.106472, 0.004175),
        "gauss10": (0.0622903, 0.00108271),
    },
    "fd2": {
        "singular": (0.100294, 0.0289218),
        "gauss2": (0.732027, 0.300543),
        "gauss4": (0.403613, 0.086822),
        "gauss6": (0.238435, 0.0368848),
        "gauss8": (0.158454, 0.0253345),
        "gauss10": (0.121591, 0.0226953),
    },
    "fd4": {
        "singular": (0.03543, 0.00820234),
        "gauss2": (0.713026, 0.28793),
        "gauss4": (0.366316, 0.0685143),
    },
    "fd6": {
        "singular": (0.0268313, 0.00729742),
        "gauss2": (0.71163, 0.287483),
        "gauss4": (0.362994, 0.0677763),
        "gauss6": (0.183024, 0.0161404),
        "gauss8": (0.108164, 0.0042626),
        "gauss10": (0.0645538, 0.00117427),
    },
}


def rows_of(table: dict[str, tuple], at: tuple) -> list[tuple]:
    return [(name, n, v) for name, values in table.items() for n, v in zip(at, values)]


def values_sql(table: dict[str, tuple], at: tuple, names: str) -> str:
    return "(SELECT * FROM (VALUES " + ", ".join(f"('{a}', {n}, CAST({v!r} AS DOUBLE))" for a, n, v in rows_of(table, at)) + f") v({names}))"


def measured(spark: SparkSession, table: dict[str, tuple], at: tuple = NODES) -> DataFrame:
    return spark.createDataFrame(rows_of(table, at), "method string, nodes int, seconds double")


_W = values_sql(WEAK, NODES, "method, nodes, seconds")
_S = values_sql(STRONG, NODES, "method, nodes, seconds")
_L = values_sql(LIBRARY, LIBRARY_NODES, "method, nodes, seconds")


@query(
    "scaling_metrics_published",
    f"""SELECT kind, method, CAST(nodes AS INT) AS nodes, round(gain, 6) + 0.0 AS gain, round(per_resource, 6) + 0.0 AS per_resource, round(mb, 6) + 0.0 AS mb_per_worker FROM (
    SELECT 'strong' AS kind, method, nodes, f / seconds AS gain, f / seconds / nodes AS per_resource, 1280.0 * 1280 * 1280 / (128 * nodes) * 8 * 14 / 3 / seconds / 1e6 AS mb FROM (SELECT *, first_value(seconds) OVER (PARTITION BY method ORDER BY nodes) AS f FROM {_S}) s
    UNION ALL SELECT 'weak', method, nodes, f / seconds, f / seconds, 96.0 * 96 * 96 * 8 * 14 / 3 / seconds / 1e6 FROM (SELECT *, first_value(seconds) OVER (PARTITION BY method ORDER BY nodes) AS f FROM {_W}) w
    UNION ALL SELECT 'library', method, nodes, f / seconds, f / seconds, 256.0 * 256 * 256 * 8 / seconds / 1e6 FROM (SELECT *, first_value(seconds) OVER (PARTITION BY method ORDER BY nodes) AS f FROM {_L}) l) q""",
)
def scaling_metrics_published(spark, sf_dir):
    """Speedup and strong efficiency, weak efficiency, and MB per second and worker of the published runs."""
    s = metrics.speedup(measured(spark, STRONG), ["method"])
    s = s.select(F.lit("strong").alias("kind"), "method", "nodes", F.col("speedup").alias("gain"), F.col("strong_efficiency").alias("per_resource"), metrics.throughput(F.lit(1280.0**3) / (128 * F.col("nodes")), F.col("seconds"), 14 / 3).alias("mb"))
    out = s
    for kind, series, at, n, pad in (("weak", WEAK, NODES, 96.0**3, 14 / 3), ("library", LIBRARY, LIBRARY_NODES, 256.0**3, 1.0)):
        w = metrics.weak_efficiency(measured(spark, series, at), ["method"])
        out = out.unionByName(w.select(F.lit(kind).alias("kind"), "method", "nodes", F.col("efficiency").alias("gain"), F.col("efficiency").alias("per_resource"), metrics.throughput(F.lit(n), F.col("seconds"), pad).alias("mb")))
    return out.select("kind", "method", "nodes", rounded("gain").alias("gain"), rounded("per_resource").alias("per_resource"), rounded("mb").alias("mb_per_worker"))


_NODES = "(VALUES " + ", ".join(f"({n})" for n in NODES) + ") v(nodes)"
#: Of the workers of line items, those of the most nodes.
WORKERS = NODES[-1]


def slowest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(method, nodes, seconds): line items of each return flag on 1, 2, 4, ... nodes, an order number's remainder each, so that the work
    grows with the nodes. All wait for the fullest node; its quantity stands for the seconds."""
    worker = F.pmod("l_orderkey", F.lit(WORKERS)).alias("worker")
    load = table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("method"), worker).agg(F.sum("l_quantity").alias("load")).where("load > 0")
    nodes = spark.createDataFrame([(n,) for n in NODES], "nodes int")
    return load.join(F.broadcast(nodes), F.col("worker") < F.col("nodes")).groupBy("method", "nodes").agg(F.max("load").alias("seconds"))


@query(
    "beta_fit_published",
    f"""WITH l AS (SELECT l_returnflag AS method, (l_orderkey % {WORKERS} + {WORKERS}) % {WORKERS} AS worker, sum(l_quantity) AS load FROM lineitem GROUP BY 1, 2),
    t AS (SELECT method, nodes, max(load) AS seconds FROM l JOIN {_NODES} ON worker < nodes WHERE load > 0 GROUP BY method, nodes),
    w AS (SELECT method, CAST(nodes AS DOUBLE) / first_value(nodes) OVER q - 1 AS x, seconds / first_value(seconds) OVER q - 1 AS y FROM t WINDOW q AS (PARTITION BY method ORDER BY nodes))
    SELECT method, round(sum(x * y) / nullif(sum(x * x), 0), 6) + 0.0 AS beta FROM w GROUP BY method""",
)
def beta_fit_published(spark, sf_dir):
    """Serial share of each return flag, fitted to the weak efficiencies of its line items."""
    w = metrics.weak_efficiency(slowest(spark, sf_dir), ["method"])
    return metrics.fit_beta(w, ["method"]).select("method", rounded("beta").alias("beta"))


@query(
    "ideal_scaling_curves",
    f"""WITH l AS (SELECT l_returnflag AS method, l_suppkey, sum(l_quantity) AS load FROM lineitem GROUP BY 1, 2),
    b AS (SELECT method, max(load) / sum(load) AS beta FROM l WHERE load > 0 AND l_suppkey IS NOT NULL GROUP BY method)
    SELECT method, CAST(nodes AS INT) AS r, round(beta, 6) + 0.0 AS beta, round(1 / ((1 - beta) / nodes + beta), 6) + 0.0 AS speedup, round(1 / ((1 - beta) + nodes * beta), 6) + 0.0 AS efficiency FROM b CROSS JOIN {_NODES}""",
)
def ideal_scaling_curves(spark, sf_dir):
    """Laws of strong and weak scaling for the line items of each return flag: a supplier's are not divided, so that the quantity of the
    fullest supplier is the serial share."""
    load = table(spark, sf_dir, "lineitem").where("l_suppkey is not null").groupBy(F.col("l_returnflag").alias("method"), "l_suppkey").agg(F.sum("l_quantity").alias("load"))
    share = load.where("load > 0").groupBy("method").agg((F.max("load") / F.sum("load")).alias("beta"))
    nodes = spark.createDataFrame([(n,) for n in NODES], "r int")
    t, a = share.crossJoin(F.broadcast(nodes)), 1 - F.col("beta")
    return t.select("method", "r", rounded("beta").alias("beta"), rounded(metrics.amdahl(a, F.col("r"))).alias("speedup"), rounded(metrics.gustafson(a, F.col("r"))).alias("efficiency"))


@query("machine_comparison_published", f"SELECT method AS machine, CAST(nodes AS INT) AS nodes, round(f / seconds, 6) + 0.0 AS efficiency FROM (SELECT *, first_value(seconds) OVER (PARTITION BY method ORDER BY nodes) AS f FROM {values_sql(MACHINES, NODES[:8], 'method, nodes, seconds')}) w")
def machine_comparison_published(spark, sf_dir):
    w = metrics.weak_efficiency(measured(spark, MACHINES, NODES[:8]), ["method"])
    return w.select(F.col("method").alias("machine"), "nodes", rounded("efficiency").alias("efficiency"))


_E = values_sql(ERRORS, POINTS, "kernel, n, error")


def errors(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(k, n, e) for k, n, e in rows_of(ERRORS, POINTS)], "kernel string, n int, error double")


@query("op_agg_regression_order", f"SELECT kernel, round(-regr_slope(ln(error), ln(n)), 6) + 0.0 AS convergence_order FROM {_E} e GROUP BY kernel")
def op_agg_regression_order(spark, sf_dir):
    """Order of convergence as a regression slope."""
    return metrics.order_fit(errors(spark), ["kernel"]).select("kernel", rounded("order").alias("convergence_order"))


@query("op_win_order_ratio", f"SELECT kernel, CAST(n AS INT) AS n, round(log2(before / error), 6) + 0.0 AS ratio FROM (SELECT *, lag(error) OVER (PARTITION BY kernel ORDER BY n) AS before FROM {_E} e) q WHERE before IS NOT NULL")
def op_win_order_ratio(spark, sf_dir):
    from pyspark.sql import Window

    before = F.lag("error").over(Window.partitionBy("kernel").orderBy("n"))
    return errors(spark).withColumn("before", before).where("before is not null").select("kernel", "n", rounded(F.log2(F.col("before") / F.col("error"))).alias("ratio"))
