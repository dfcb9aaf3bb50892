"""Line transforms of table columns against dense SQL sums."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import transforms as T
from ..functions.transforms_sql import dense
from ..plans.boundary import LineTransform, impose, refill, transform_table
from ..plans.grid import CELL, NODE, PAIRS, PERIODIC, Axis
from ..queries import query, rounded
from ..sources.fields import day, lines, table

N = 64
#: Embedding values by position; kinds with an end point see the first value again at the end.
POINTS = "SELECT vec_id AS key, CAST(j AS BIGINT) AS j, CAST(embedding[j + 1] AS DOUBLE) AS v FROM embeddings CROSS JOIN (SELECT CAST(range AS BIGINT) AS j FROM range(0, 64)) r UNION ALL SELECT vec_id, 64, CAST(embedding[1] AS DOUBLE) FROM embeddings"


def _round(sql: str, key: str = "key") -> str:
    return f"SELECT {key}, CAST(k AS INT) AS k, round(y, 6) + 0.0 AS y FROM ({sql}) q"


def embedding_lines(spark: SparkSession, sf_dir: str, closed: bool) -> DataFrame:
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), T.as_doubles(F.col("embedding")).alias("line"))
    return e.withColumn("line", F.concat("line", F.slice("line", 1, 1))) if closed else e


def exploded(df: DataFrame, first: int = 0) -> DataFrame:
    out = df.select("key", F.posexplode("y").alias("k", "y"))
    return out.select("key", (F.col("k") + first).cast("int").alias("k"), rounded("y").alias("y"))


@query("dft_embedding_lines", f"SELECT a.key, CAST(a.k AS INT) AS k, round(a.y, 6) + 0.0 AS re, round(b.y, 6) + 0.0 AS im FROM ({dense('dft_re', f'({POINTS}) p', N)}) a JOIN ({dense('dft_im', f'({POINTS}) p', N)}) b ON a.key = b.key AND a.k = b.k")
def dft_embedding_lines(spark, sf_dir):
    y = embedding_lines(spark, sf_dir, False).select("key", T.dft_r2c_column()("line").alias("y"))
    y = y.select("key", F.posexplode(F.arrays_zip("y.re", "y.im")).alias("k", "p"))
    return y.select("key", "k", rounded("p.re").alias("re"), rounded("p.im").alias("im"))


def _kinds():
    for name, column in (("dct", T.dct_column), ("dst", T.dst_column)):
        for kind in (1, 2, 3, 4):
            closed = (name, kind) in (("dct", 1), ("dst", 1), ("dst", 3))

            def run(spark, sf_dir, name=name, kind=kind, column=column, closed=closed):
                e = embedding_lines(spark, sf_dir, closed)
                if (name, kind) == ("dst", 1):
                    e = e.withColumn("line", F.slice("line", 2, N - 1))
                elif (name, kind) == ("dst", 3):
                    e = e.withColumn("line", F.slice("line", 2, N))
                first = 1 if (name, kind) in (("dst", 1), ("dst", 2)) else 0
                return exploded(e.select("key", column(kind)("line").alias("y")), first)

            query(f"{name}{kind}_embedding", _round(dense(f"{name}{kind}", f"({POINTS}) p", N)))(run)


_kinds()


@query(
    "roundtrip_embedding",
    "SELECT CAST(kind AS VARCHAR) AS kind, 0.0 + round(0.0, 6) AS e_inf FROM (VALUES " + ", ".join(f"('{n}{k}')" for n in ("dct", "dst") for k in (1, 2, 3, 4)) + ", ('dft')) v(kind)",
)
def roundtrip_embedding(spark, sf_dir):
    """Largest difference after transform and inverse, per kind; zero after rounding."""
    e = embedding_lines(spark, sf_dir, False)
    out = None
    pairs = [(f"{n}{k}", c(k), c(k, inverse=True)) for n, c in (("dct", T.dct_column), ("dst", T.dst_column)) for k in (1, 2, 3, 4)]
    for kind, forward, back in pairs:
        d = e.select("line", back(forward("line")).alias("again"))
        d = d.select(F.aggregate(F.zip_with("line", "again", lambda a, b: F.abs(a - b)), F.lit(0.0), lambda s, x: F.greatest(s, x)).alias("d")).agg(F.max("d").alias("d")).select(F.lit(kind).alias("kind"), rounded("d").alias("e_inf"))
        out = d if out is None else out.unionByName(d)
    f = e.select("line", T.dft_r2c_column()("line").alias("y")).select("line", T.dft_c2r_column(N)("y.re", "y.im").alias("again"))
    f = f.select(F.aggregate(F.zip_with("line", "again", lambda a, b: F.abs(a - b)), F.lit(0.0), lambda s, x: F.greatest(s, x)).alias("d"))
    return out.unionByName(f.agg(F.max("d").alias("d")).select(F.lit("dft").alias("kind"), rounded("d").alias("e_inf")))


@query(
    "boundary_transform_table",
    """WITH o AS (SELECT CASE WHEN o_orderkey % 2 = 0 THEN 'cell' ELSE 'node' END AS layout, CAST((o_custkey % 10 + 10) % 10 AS INT) AS pair, count(*) AS n FROM orders WHERE o_orderkey IS NOT NULL GROUP BY 1, 2)
    SELECT a.layout, l AS "left", r AS "right", CAST(CASE WHEN l = 'periodic' THEN 3 WHEN l = 'unbounded' AND r = 'unbounded' THEN 4 WHEN l = 'unbounded' OR r = 'unbounded' THEN 2 ELSE 1 END AS INT) AS category,
    CASE WHEN l IN ('periodic') OR (l = 'unbounded' AND r = 'unbounded') THEN 'dft' WHEN (CASE WHEN l = 'unbounded' THEN r ELSE l END) = 'even' THEN 'dct' ELSE 'dst' END AS transform,
    CAST(CASE WHEN l = 'periodic' OR (l = 'unbounded' AND r = 'unbounded') THEN 0 WHEN l = r OR l = 'unbounded' OR r = 'unbounded' THEN CASE WHEN a.layout = 'node' THEN 1 ELSE 2 END WHEN a.layout = 'node' THEN 3 ELSE 4 END AS INT) AS kind, coalesce(n, 0) AS orders
    FROM (VALUES ('cell'), ('node')) a(layout) CROSS JOIN (VALUES ('even', 'even', 0), ('odd', 'odd', 1), ('odd', 'even', 2), ('even', 'odd', 3), ('periodic', 'periodic', 4), ('unbounded', 'unbounded', 5), ('even', 'unbounded', 6), ('odd', 'unbounded', 7), ('unbounded', 'even', 8), ('unbounded', 'odd', 9)) b(l, r, number)
    LEFT JOIN o ON o.layout = a.layout AND pair = number""",
)
def boundary_transform_table(spark, sf_dir):
    """The choice of transform for both layouts and all ten boundary pairs, with the orders whose number and customer choose it."""
    layout = F.when(F.col("o_orderkey") % 2 == 0, CELL).otherwise(NODE)
    pair = F.pmod("o_custkey", F.lit(len(PAIRS))).alias("pair")
    o = table(spark, sf_dir, "orders").where("o_orderkey is not null").groupBy(layout.alias("layout"), pair).agg(F.count("*").alias("orders"))
    number = F.array_position(F.lit([" ".join(p) for p in PAIRS]), F.concat_ws(" ", "left", "right")) - 1
    choices = transform_table(spark).withColumn("pair", number)
    out = choices.join(o, ["layout", "pair"], "left")
    return out.select("layout", "left", "right", "category", "transform", "kind", F.coalesce("orders", F.lit(0)).cast("long").alias("orders"))


@query("boundary_roundtrip_embedding", "SELECT l AS \"left\", r AS \"right\", layout, round(0.0, 6) + 0.0 AS e_inf FROM (VALUES ('cell'), ('node')) a(layout) CROSS JOIN (VALUES " + ", ".join(f"('{l}', '{r}')" for l, r in PAIRS) + ") b(l, r)")
def boundary_roundtrip_embedding(spark, sf_dir):
    """Inverse after forward for all boundary pairs and layouts on real lines, forced points imposed before."""
    import numpy as np
    import pandas as pd

    out = None
    for layout in (CELL, NODE):
        for left, right in PAIRS:
            axis = Axis(N, left, right, layout)
            e = embedding_lines(spark, sf_dir, layout == NODE)
            if (left, right) != (PERIODIC, PERIODIC):
                e = e.withColumn("line", impose(F.col("line"), axis))
            else:
                e = e.withColumn("line", refill(F.col("line"), axis))

            def run(frames, axis=axis):
                t = LineTransform(axis)
                for p in frames:
                    x = np.stack(p["line"].to_numpy()) if len(p) else np.zeros((0, axis.points))
                    yield pd.DataFrame({"d": np.abs(t.backward(t.forward(x)) - x).max(1) if len(p) else []})

            d = e.select("line").mapInPandas(run, "d double").agg(F.max("d").alias("d"))
            d = d.select(F.lit(left).alias("left"), F.lit(right).alias("right"), F.lit(layout).alias("layout"), rounded("d").alias("e_inf"))
            out = d if out is None else out.unionByName(d)
    return out


HOURS = "SELECT event_type AS key, CAST(date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS BIGINT) AS j, sum(value) / 1000 AS v FROM events GROUP BY 1, 2"


def hourly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, j, v): sums per hour of the month, in thousands."""
    hour = F.floor((F.unix_timestamp("ts") - F.unix_timestamp(F.lit("2024-01-01").cast("timestamp"))) / 3600).cast("int")
    return table(spark, sf_dir, "events").groupBy("event_type", hour.alias("j")).agg((F.sum("value") / 1000).alias("v"))


def power(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, k, power) of the hourly lines."""
    y = lines(hourly(spark, sf_dir), "event_type", 720).select("event_type", T.dft_r2c_column()("line").alias("y"))
    y = y.select("event_type", F.posexplode(F.zip_with("y.re", "y.im", lambda a, b: a * a + b * b)).alias("k", "power"))
    return y


POWER = f"SELECT a.key AS event_type, a.k, a.y * a.y + b.y * b.y AS power FROM ({dense('dft_re', f'({HOURS}) p', 720)}) a JOIN ({dense('dft_im', f'({HOURS}) p', 720)}) b ON a.key = b.key AND a.k = b.k"


@query("hourly_power_spectrum", f"SELECT event_type, CAST(k AS INT) AS k, round(power, 6) + 0.0 AS power, CAST(r AS INT) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY power DESC, k) AS r FROM ({POWER}) p) q WHERE r <= 5")
def hourly_power_spectrum(spark, sf_dir):
    from pyspark.sql import Window

    w = Window.partitionBy("event_type").orderBy(F.desc("power"), "k")
    p = power(spark, sf_dir).withColumn("rank", F.row_number().over(w)).where("rank <= 5")
    return p.select("event_type", "k", rounded("power").alias("power"), "rank")


def _nation(table_: str, key: str, balance: str) -> str:
    return f"SELECT 0 AS key, CAST({key} AS BIGINT) AS j, sum({balance}) / 1e4 AS v FROM {table_} WHERE {key} BETWEEN 0 AND 24 GROUP BY 2"


def _nation_line(spark, sf_dir, name, key, balance):
    t = table(spark, sf_dir, name).groupBy(F.col(key).alias("j")).agg((F.sum(balance) / 1e4).alias("v")).withColumn("key", F.lit(0))
    return lines(t, "key", 25)


@query(
    "node_cell_layout_nation",
    f"SELECT 'node' AS layout, CAST(k AS INT) AS k, round(y, 6) + 0.0 AS y FROM ({dense('dct1', '(' + _nation('customer', 'c_nationkey', 'c_acctbal') + ') p', 24)}) a UNION ALL SELECT 'cell', CAST(k AS INT), round(y, 6) + 0.0 FROM ({dense('dct2', '(' + _nation('customer', 'c_nationkey', 'c_acctbal') + ') p', 24)}) b",
)
def node_cell_layout_nation(spark, sf_dir):
    """25 nations as a node-centred line of 24 intervals, and the first 24 as a cell-centred line."""
    c = _nation_line(spark, sf_dir, "customer", "c_nationkey", "c_acctbal")
    node = exploded(c.select("key", T.dct_column(1)("line").alias("y"))).withColumn("layout", F.lit("node"))
    cell = exploded(c.select("key", T.dct_column(2)(F.slice("line", 1, 24)).alias("y"))).withColumn("layout", F.lit("cell"))
    return node.unionByName(cell).select("layout", "k", "y")


@query("supplier_balance_line", f"SELECT CAST(k AS INT) AS k, round(y, 6) + 0.0 AS y FROM ({dense('dst1', '(' + _nation('supplier', 's_nationkey', 's_acctbal') + ') p', 24)}) a")
def supplier_balance_line(spark, sf_dir):
    s = _nation_line(spark, sf_dir, "supplier", "s_nationkey", "s_acctbal")
    return exploded(s.select("key", T.dst_column(1)(F.slice("line", 2, 23)).alias("y")), 1).select("k", "y")


LANGS = "SELECT lang AS key, CAST(doc_id % 64 AS BIGINT) AS j, sum(n_chars) / 1e4 AS v FROM documents d LEFT JOIN labels l USING (doc_id) WHERE coalesce(toxic, 0) = 0 GROUP BY 1, 2"


@query("text_length_line", f"SELECT key AS lang, CAST(k AS INT) AS k, round(y, 6) + 0.0 AS y FROM ({dense('dct2', f'({LANGS}) p', 64)}) a WHERE k < 8")
def text_length_line(spark, sf_dir):
    """Text lengths by document number, documents not labelled toxic: low modes per language."""
    d = table(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars").join(table(spark, sf_dir, "labels").select("doc_id", "toxic"), "doc_id", "left")
    d = d.where(F.coalesce("toxic", F.lit(0)) == 0).groupBy("lang", (F.col("doc_id") % 64).alias("j")).agg((F.sum("n_chars") / 1e4).alias("v"))
    y = exploded(lines(d, "lang", 64).select(F.col("lang").alias("key"), T.dct_column(2)("line").alias("y"))).where("k < 8")
    return y.withColumnRenamed("key", "lang")


_TURNS = "SELECT conv_id, CAST(turn AS BIGINT) AS j, sum(length(text)) / 1e3 AS v FROM conversations GROUP BY 1, 2"


@query("conversation_turn_line", f"WITH c AS ({_TURNS}), n AS (SELECT greatest(16, max(j) + 1) AS n FROM c), m AS (SELECT n, unnest(range(0, n)) AS k FROM n) SELECT conv_id, CAST(k AS INT) AS k, round(sum(2 * v * cos(pi() * k * (j + 0.5) / n)), 6) + 0.0 AS y FROM c CROSS JOIN m GROUP BY conv_id, k")
def conversation_turn_line(spark, sf_dir):
    """Turn lengths, a ragged line per conversation padded to the longest one, sixteen turns at least."""
    c = table(spark, sf_dir, "conversations").groupBy("conv_id", F.col("turn").alias("j")).agg((F.sum(F.length("text")) / 1e3).alias("v"))
    # one number decides the length of all lines
    n = max(16, (c.agg(F.max("j")).first()[0] or 0) + 1)
    y = exploded(lines(c, "conv_id", n).select(F.col("conv_id").alias("key"), T.dct_column(2)("line").alias("y")))
    return y.withColumnRenamed("key", "conv_id")


def _size_line(name: str, id_: str, text: str, key: str):
    sql = f"SELECT 0 AS key, CAST({id_} % 64 AS BIGINT) AS j, sum(length({text})) / 1e4 AS v FROM {name} GROUP BY 2"

    @query(key, f"SELECT CAST(k AS INT) AS k, round(y, 6) + 0.0 AS y FROM ({dense('dst2', f'({sql}) p', 64)}) a")
    def run(spark, sf_dir):
        t = table(spark, sf_dir, name).groupBy((F.col(id_) % 64).alias("j")).agg((F.sum(F.length(text)) / 1e4).alias("v")).withColumn("key", F.lit(0))
        return exploded(lines(t, "key", 64).select("key", T.dst_column(2)("line").alias("y")), 1).select("k", "y")


_size_line("pages", "page_id", "html", "page_size_line")
_size_line("benchmark", "item_id", "text", "benchmark_size_line")


PART = "SELECT CAST((p_size - 1) % 50 AS BIGINT) AS a, CAST(CAST(regexp_extract(p_brand, '([0-9]+)', 1) AS INT) % 16 AS BIGINT) AS b, avg(p_retailprice) / 1e3 AS v FROM part GROUP BY 1, 2"


@query(
    "part_plane",
    "SELECT CAST(ka AS INT) AS ka, CAST(k AS INT) AS kb, round(y, 6) + 0.0 AS y FROM (" + dense("dct2", "(SELECT k AS ka, b AS j, y AS v FROM (" + dense("dct2", f"(SELECT a AS j, b, v FROM ({PART}) p0) p1", 50, "b") + ") q1) p2", 16, "ka") + ") q2 WHERE ka < 8",
)
def part_plane(spark, sf_dir):
    """Two-dimensional cosine transform of prices over size and brand: two line passes with one switch."""
    p = table(spark, sf_dir, "part")
    brand = F.regexp_extract("p_brand", "([0-9]+)", 1).cast("int") % 16
    p = p.groupBy(((F.col("p_size") - 1) % 50).alias("j"), brand.alias("b")).agg((F.avg("p_retailprice") / 1e3).alias("v"))
    first = lines(p, "b", 50).select("b", F.posexplode(T.dct_column(2)("line")).alias("ka", "v"))
    second = lines(first, "ka", 16, "b").select("ka", F.posexplode(T.dct_column(2)("line")).alias("kb", "y")).where("ka < 8")
    return second.select("ka", "kb", rounded("y").alias("y"))


__all__ = ["day", "hourly", "power"]
