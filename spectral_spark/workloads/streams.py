"""Streaming workloads: each runs over the whole event table with an available-now trigger and returns its result table."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import poisson
from ..plans.grid import CELL, UNBOUNDED, Axis, GridSpec
from ..queries import query, rounded
from ..sources.fields import cube_events, rasterise, table
from ..streaming import fields as S
from .solves import C2, GRID, N, _cells_sql, _kernel3

#: Windows are emitted once the watermark (the last event less two hours, in whole milliseconds) has passed their end.
MARK = "(SELECT date_trunc('millisecond', max(ts)) - INTERVAL 2 HOUR FROM events)"


@query("stream_tumbling_cells", f"SELECT date_trunc('hour', ts) AS hour, event_type, round(sum(value), 4) + 0.0 AS total, count(*) AS n FROM events GROUP BY 1, 2 HAVING date_trunc('hour', ts) + INTERVAL 1 HOUR <= {MARK}")
def stream_tumbling_cells(spark, sf_dir):
    t = S.finish(S.tumbling_cells(S.event_stream(spark, sf_dir)))
    return t.select("hour", "event_type", rounded("total", 4).alias("total"), "n")


@query("stream_sliding_cells", f"SELECT s AS start, event_type, round(sum(value), 4) + 0.0 AS total FROM (SELECT date_trunc('hour', ts) - to_hours(CAST(k AS INT)) AS s, event_type, value FROM events CROSS JOIN range(0, 6) r(k)) e GROUP BY 1, 2 HAVING s + INTERVAL 6 HOUR <= {MARK}")
def stream_sliding_cells(spark, sf_dir):
    return S.finish(S.sliding_cells(S.event_stream(spark, sf_dir))).select("start", "event_type", rounded("total", 4).alias("total"))


@query(
    "stream_session_lines",
    f"""WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
    s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM g)
    SELECT user_id, min(ts) AS start, count(*) AS n, round(sum(value), 4) + 0.0 AS total FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 1 HOUR <= {MARK}""",
)
def stream_session_lines(spark, sf_dir):
    return S.finish(S.session_lines(S.event_stream(spark, sf_dir))).select("user_id", "start", "n", rounded("total", 4).alias("total"))


@query("stream_dedup", "SELECT event_id, event_type, round(value, 4) + 0.0 AS value FROM events")
def stream_dedup(spark, sf_dir):
    """The stream united with itself: each event once."""
    e = S.event_stream(spark, sf_dir)
    return S.finish(S.deduplicated(e.unionByName(S.event_stream(spark, sf_dir)))).select("event_id", "event_type", rounded("value", 4).alias("value"))


@query("stream_late_rows", "SELECT count(DISTINCT hash(date_trunc('hour', ts), event_type)) AS late_cells FROM events WHERE ts < TIMESTAMP '2024-01-15' AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= (SELECT date_trunc('millisecond', max(ts)) - INTERVAL 2 HOUR FROM events)")
def stream_late_rows(spark, sf_dir):
    """Cells of the first half of the month that come behind the watermark (rows of a cell are combined before the count)."""
    _, dropped = S.late_rows(spark, sf_dir)
    return spark.createDataFrame([(dropped,)], "late_cells long")


_CELLS = "SELECT event_type, CAST(hour(ts) AS INT) AS hour_of_day, count(*) AS n, round(sum(value), 4) + 0.0 AS total FROM events GROUP BY 1, 2"


def _last_totals(t):
    t = t.groupBy("event_type", "hour_of_day").agg(F.max("n").alias("n"), F.max("total").alias("total"))
    return t.select("event_type", "hour_of_day", "n", rounded("total", 4).alias("total"))


@query("stream_group_state", _CELLS)
def stream_group_state(spark, sf_dir):
    """Running totals in a group's one state."""
    return _last_totals(S.finish(S.running_field(S.event_stream(spark, sf_dir))))


@query("stream_stateful_field", _CELLS)
def stream_stateful_field(spark, sf_dir):
    """Running totals by a stateful processor with timers; its state store is set for this query and put back."""
    key, value = S.ROCKS
    before = spark.conf.get(key)
    spark.conf.set(key, value)
    try:
        return _last_totals(S.finish(S.running_cells(S.event_stream(spark, sf_dir))))
    finally:
        spark.conf.set(key, before)


@query("stream_join_dimension", "SELECT event_id, CAST(CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS INT) AS axis, round(value, 4) + 0.0 AS value FROM events WHERE event_type IN ('click', 'error', 'purchase', 'signup', 'view')")
def stream_join_dimension(spark, sf_dir):
    d = spark.createDataFrame([(t, i) for i, t in enumerate(("click", "error", "purchase", "signup", "view"))], "event_type string, axis int")
    return S.finish(S.with_dictionary(S.event_stream(spark, sf_dir), F.broadcast(d))).select("event_id", "axis", rounded("value", 4).alias("value"))


_SOLVED = _cells_sql(f"SELECT px AS ix, py AS iy, pz AS iz, sum(v * ({_kernel3('(px - ix) * (px - ix) + (py - iy) * (py - iy) + (pz - iz) * (pz - iz)')})) / {N**3} AS v FROM ({C2}) f CROSS JOIN {GRID} g GROUP BY 1, 2, 3")


def _increments(spark, sf_dir, solve):
    e = S.event_stream(spark, sf_dir)

    def step(batch):
        from ..sources.fields import day

        cells = rasterise(batch, F.floor(day("ts", "2024-01-01") * N / 30), F.floor(F.hour("ts") * N / 24), F.get_json_object("props", "$.k").cast("int") % N, F.col("value") / 1e3)
        return solve(cells)

    return S.incremental_solve(spark, e, step, ["ix", "iy", "iz"])


@query("stream_incremental_solve", _SOLVED)
def stream_incremental_solve(spark, sf_dir):
    """Micro-batches solved alone and added up."""
    spec = GridSpec.of(*[Axis(N, UNBOUNDED, UNBOUNDED, CELL)] * 3)
    out = _increments(spark, sf_dir, lambda cells: poisson.solve(cells, spec, "singular"))
    return out.select("ix", "iy", "iz", rounded("v").alias("v"))


@query("streaming_field_events", f"SELECT CAST(ix AS INT) AS ix, CAST(iy AS INT) AS iy, CAST(iz AS INT) AS iz, round(v, 6) + 0.0 AS v FROM ({C2}) f")
def streaming_field_events(spark, sf_dir):
    """The event cube kept by a stream equals the batch cube."""
    return _increments(spark, sf_dir, lambda cells: cells).select("ix", "iy", "iz", rounded("v").alias("v"))


__all__ = ["cube_events", "table"]
