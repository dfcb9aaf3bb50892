"""Index distributions, send orders, block lists."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import metrics
from ..operators.exchange import Workers, block_table, fan_in, send_schedule
from ..plans.boundary import LineTransform
from ..plans.distribution import Distribution, balance
from ..plans.grid import CELL, PERIODIC, UNBOUNDED, Axis, GridSpec
from ..plans.planner import build, message_model, padding_factor, switches, volumes
from ..queries import query, rounded
from ..sources.fields import day, table

KEYS = 6000


def _sql_owner(kind: str, i: str, n: int, p: int) -> str:
    b, r = divmod(n, p)
    if kind == "proportional":
        return f"CAST(ceil(({i} + 1) * {p} / {n}.0) - 1 AS INT)"
    if not r:
        return f"CAST({i} // {max(b, 1)} AS INT)"
    s = p // r if kind == "strided" else 1
    g = s * b + 1
    return f"CAST(CASE WHEN {i} // {g} < {r} THEN ({i} // {g}) * {s} + least(({i} % {g}) // {b}, {s - 1}) ELSE ({i} - {r * g}) // {b} + {r * s} END AS INT)"


def _owners():
    for kind in ("strided", "first_heavy", "proportional"):
        parts = " UNION ALL ".join(f"SELECT {p} AS p, {_sql_owner(kind, f'(l_orderkey % {KEYS})', KEYS, p)} AS worker FROM lineitem" for p in (7, 48, 96))

        def run(spark, sf_dir, kind=kind):
            t, out = table(spark, sf_dir, "lineitem").select("l_orderkey"), None
            for p in (7, 48, 96):
                part = t.select(F.lit(p).alias("p"), Distribution(KEYS, p, kind).owner(F.col("l_orderkey") % KEYS).alias("worker"))
                out = part if out is None else out.unionByName(part)
            return out.groupBy("p", "worker").agg(F.count("*").alias("n"))

        query(f"owner_{kind}_lineitem", f"SELECT p, worker, count(*) AS n FROM ({parts}) q GROUP BY p, worker")(run)


_owners()


@query(
    "distribution_examples",
    "WITH l AS (SELECT (l_orderkey % 32 + 32) % 32 AS i, count(*) AS n FROM lineitem GROUP BY 1), w AS (SELECT *, sum(n) OVER (PARTITION BY p ORDER BY worker) AS after FROM (VALUES (7,0,5),(7,1,5),(7,2,5),(7,3,5),(7,4,4),(7,5,4),(7,6,4),(6,0,5),(6,1,5),(6,2,6),(6,3,5),(6,4,5),(6,5,6)) v(p, worker, n)) SELECT CAST(p AS INT) AS p, CAST(worker AS INT) AS worker, CAST(w.n AS BIGINT) AS n, count(i) AS held, CAST(coalesce(sum(l.n), 0) AS BIGINT) AS line_items FROM w LEFT JOIN l ON i >= after - w.n AND i < after GROUP BY ALL",
)
def distribution_examples(spark, sf_dir):
    """32 indices over 7 and over 6 workers, the worked examples: how many of its indices the order numbers of the line items hold, and
    how many line items that are."""
    owners = None
    for p in (7, 6):
        t = Distribution(32, p).table(spark).withColumn("p", F.lit(p))
        owners = t if owners is None else owners.unionByName(t)
    lines = table(spark, sf_dir, "lineitem").groupBy(F.pmod("l_orderkey", F.lit(32)).alias("i")).agg(F.count("*").alias("lines"))
    # 32 indices
    out = owners.join(F.broadcast(lines), (F.col("i") >= F.col("first")) & (F.col("i") < F.col("after")), "left")
    n = (F.col("after") - F.col("first")).alias("n")
    return out.groupBy("p", "worker", n).agg(F.count("i").alias("held"), F.coalesce(F.sum("lines"), F.lit(0)).cast("long").alias("line_items"))


_DOCS = " UNION ALL ".join(f"SELECT '{k}' AS kind, {_sql_owner(k, '(doc_id % 500)', 500, 48)} AS worker, n_chars FROM documents" for k in ("strided", "first_heavy", "proportional"))


@query("balance_nodes_documents", f"SELECT kind, CAST(node AS INT) AS node, sum(load) AS node_load, max(load) AS max_worker, min(load) AS min_worker FROM (SELECT kind, worker, worker // 8 AS node, CAST(sum(n_chars) AS BIGINT) AS load FROM ({_DOCS}) d GROUP BY 1, 2) l GROUP BY 1, 2")
def balance_nodes_documents(spark, sf_dir):
    """Characters per group of eight workers under the three distributions."""
    d, out = table(spark, sf_dir, "documents").select("doc_id", "n_chars"), None
    for kind in ("strided", "first_heavy", "proportional"):
        part = d.withColumn("worker", Distribution(500, 48, kind).owner(F.col("doc_id") % 500))
        b = balance(part, "worker", F.col("n_chars"), 8).withColumn("kind", F.lit(kind))
        out = b if out is None else out.unionByName(b)
    return out.select("kind", "node", F.col("node_load").cast("decimal(38,0)").alias("node_load"), "max_worker", "min_worker")


@query("send_fan_in", "SELECT CAST(p AS INT) AS p, o AS send_order, CAST(r AS INT) AS round, CAST(CASE WHEN o = 'naive' THEN p ELSE 1 END AS BIGINT) AS max_fan_in FROM (VALUES (8), (16), (64)) a(p) CROSS JOIN (VALUES ('naive'), ('rotated')) b(o) CROSS JOIN (SELECT range AS r FROM range(0, 64)) c WHERE r < p")
def send_fan_in(spark, sf_dir):
    """Senders at the busiest receiver, by round: all of them in the naive order, one in the rotated order."""
    out = None
    for p in (8, 16, 64):
        for order in ("naive", "rotated"):
            f = fan_in(send_schedule(spark, p, order)).select(F.lit(p).alias("p"), F.lit(order).alias("send_order"), "round", "max_fan_in")
            out = f if out is None else out.unionByName(f)
    return out


def cube(n: int = 32) -> GridSpec:
    return GridSpec.of(*[Axis(n, UNBOUNDED, UNBOUNDED, CELL)] * 3)


_R = "(SELECT CAST(range AS BIGINT) AS r FROM range(0, 2))"


def _starts(n: int, p: int, r: str) -> str:
    b, e = divmod(n, p)
    s = p // e if e else p
    return f"({r} * {b} + least({r} // {s}, {e}))"


#: Line items on the slots of the first axis and the points of the others.
_CELLS = "SELECT (l_partkey % 33 + 33) % 33 AS i0, (l_suppkey % 32 + 32) % 32 AS i1, (date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) % 32 + 32) % 32 AS i2, count(*) AS n FROM lineitem GROUP BY 1, 2, 3"


@query(
    "block_table_32",
    f"""WITH w AS (SELECT CAST(a.range AS BIGINT) AS a, CAST(b.range AS BIGINT) AS b FROM range(0, 2) a CROSS JOIN range(0, 3) b),
    t AS (SELECT CAST(s.a * 3 + s.b AS INT) AS src, CAST(d.a * 3 + d.b AS INT) AS dst,
      {_starts(33, 2, 'd.a')} AS o0, {_starts(32, 2, 's.a')} AS o1, {_starts(32, 3, 's.b')} AS o2,
      {_starts(33, 2, '(d.a + 1)')} - {_starts(33, 2, 'd.a')} AS n0, {_starts(32, 2, '(s.a + 1)')} - {_starts(32, 2, 's.a')} AS n1, {_starts(32, 3, '(s.b + 1)')} - {_starts(32, 3, 's.b')} AS n2,
      8 * ({_starts(33, 2, '(d.a + 1)')} - {_starts(33, 2, 'd.a')}) * ({_starts(32, 2, '(s.a + 1)')} - {_starts(32, 2, 's.a')}) * ({_starts(32, 3, '(s.b + 1)')} - {_starts(32, 3, 's.b')}) AS bytes
    FROM w s JOIN w d ON s.b = d.b)
    SELECT src, dst, o0, o1, o2, n0, n1, n2, bytes, count(n) AS held, CAST(coalesce(sum(n), 0) AS BIGINT) AS line_items
    FROM t LEFT JOIN ({_CELLS}) c ON i0 >= o0 AND i0 < o0 + n0 AND i1 >= o1 AND i1 < o1 + n1 AND i2 >= o2 AND i2 < o2 + n2 GROUP BY ALL""",
)
def block_table_32(spark, sf_dir):
    """Blocks of the first switch on 32^3 cells, open boundaries, 2 x 3 workers: how many cells of each the line items hold, and how
    many line items that are."""
    blocks = block_table(spark, Workers(build(cube()), 6), 0, 1)
    index = [F.pmod("l_partkey", F.lit(33)), F.pmod("l_suppkey", F.lit(32)), F.pmod(day("l_shipdate", "1995-01-01"), F.lit(32))]
    cells = table(spark, sf_dir, "lineitem").groupBy(*[i.alias(f"i{a}") for a, i in enumerate(index)]).agg(F.count("*").alias("n"))
    inside = [(F.col(f"i{a}") >= F.col(f"o{a}")) & (F.col(f"i{a}") < F.col(f"o{a}") + F.col(f"n{a}")) for a in range(3)]
    # twelve blocks
    held = cells.join(F.broadcast(blocks), inside[0] & inside[1] & inside[2]).groupBy("src", "dst").agg(F.count("*").alias("held"), F.sum("n").alias("line_items"))
    return blocks.join(held, ["src", "dst"], "left").select(*blocks.columns, *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("held", "line_items")])


@query(
    "switch_cost_32",
    "SELECT CAST(s AS INT) AS switch, strategy, CAST(blocks AS BIGINT) AS blocks, CAST(bytes AS BIGINT) AS bytes, CAST(largest AS BIGINT) AS largest_block, CAST(CASE WHEN by_cell THEN bytes // 8 ELSE blocks END AS BIGINT) AS rows, CAST(copies * bytes AS DOUBLE) AS copied_bytes FROM (VALUES (1, 12, 8 * 33 * 32 * 32, 8 * 17 * 16 * 11), (2, 18, 8 * 33 * 64 * 32, 8 * 17 * 22 * 11)) a(s, blocks, bytes, largest) CROSS JOIN (VALUES ('packed_barrier', 2, false), ('batched_async', 1, false), ('unpacked_direct', 1, true)) b(strategy, copies, by_cell)",
)
def switch_cost_32(spark, sf_dir):
    """Blocks, bytes, rows and copies of the two switches per strategy."""
    return metrics.switch_cost(spark, Workers(build(cube()), 6))


@query(
    "padding_factors",
    "SELECT kind, CAST(switches AS INT) AS switches, CAST(v1 AS BIGINT) AS v1, CAST(v2 AS BIGINT) AS v2, CAST(v3 AS BIGINT) AS v3, round(f, 6) + 0.0 AS factor FROM (VALUES ('unbounded', 2, 32768, 33792, 67584, 14.0 / 3), ('periodic', 2, 32768, 17408, 17408, 1.0)) v(kind, switches, v1, v2, v3, f)",
)
def padding_factors(spark, sf_dir):
    """Values that each switch moves, and the mean transform length over the grid: 14/3 for three open axes."""
    rows = []
    for kind, spec in (("unbounded", cube()), ("periodic", GridSpec.of(*[Axis(32, PERIODIC, PERIODIC, CELL)] * 3))):
        rows.append((kind, switches(spec, 0), *volumes(spec), float(padding_factor(spec))))
    return spark.createDataFrame(rows, "kind string, switches int, v1 long, v2 long, v3 long, f double").select("kind", "switches", "v1", "v2", "v3", rounded("f").alias("factor"))


@query("message_counts", "SELECT decomposition, CAST(p AS INT) AS p, CAST(CASE WHEN decomposition = 'slab' THEN 1 ELSE 2 END AS INT) AS switches, CASE WHEN decomposition = 'slab' THEN CAST(p AS DOUBLE) ELSE round(sqrt(p), 6) END + 0.0 AS peers FROM (VALUES ('slab'), ('pencil')) a(decomposition) CROSS JOIN (VALUES (16), (64), (1024)) b(p)")
def message_counts(spark, sf_dir):
    rows = [(d, p, int(m["switches"]), float(m["peers"])) for d in ("slab", "pencil") for p in (16, 64, 1024) for m in [message_model(1280, p, d)]]
    return spark.createDataFrame(rows, "decomposition string, p int, switches int, peers double").withColumn("peers", rounded("peers"))


@query("mode_frequencies", "SELECT 'even-even' AS bc, CAST(k AS INT) AS slot, round(pi() * k, 6) + 0.0 AS omega FROM (SELECT range AS k FROM range(0, 9)) a UNION ALL SELECT 'odd-even', CAST(k AS INT), round(pi() * (k + 0.5), 6) + 0.0 FROM (SELECT range AS k FROM range(0, 8)) b UNION ALL SELECT 'periodic-periodic', CAST(k AS INT), round(2 * pi() * k, 6) + 0.0 FROM (SELECT range AS k FROM range(0, 5)) c UNION ALL SELECT 'unbounded-unbounded', CAST(k AS INT), round(pi() * k, 6) + 0.0 FROM (SELECT range AS k FROM range(0, 9)) d UNION ALL SELECT 'even-unbounded', CAST(k AS INT), round(pi() * k / 2, 6) + 0.0 FROM (SELECT range AS k FROM range(0, 17)) e")
def mode_frequencies(spark, sf_dir):
    """Slots and frequencies of an axis of eight nodes-apart intervals."""
    from ..plans.boundary import omega as omega_column

    out = None
    for left, right in (("even", "even"), ("odd", "even"), ("periodic", "periodic"), ("unbounded", "unbounded"), ("even", "unbounded")):
        line = LineTransform(Axis(8, left, right))
        t = spark.range(line.slots).select(F.lit(f"{left}-{right}").alias("bc"), F.col("id").cast("int").alias("slot"), omega_column(line, F.col("id")).alias("omega"))
        out = t if out is None else out.unionByName(t)
    return out.withColumn("omega", rounded("omega"))
