"""Accuracy and scaling measures, as DataFrame expressions; and timings of our own runs."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.planner import TransformPlan, padding_factor
from .exchange import Workers, block_table

KEYS = ["ix", "iy", "iz"]


def e_inf(df: DataFrame, ref: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Largest absolute difference over all points (and components, if both have them); one row."""
    keys = keys or [*KEYS, *(["comp"] if "comp" in df.columns and "comp" in ref.columns else [])]
    both = df.select(*keys, F.col("v").alias("a")).join(ref.select(*keys, F.col("v").alias("b")), keys, "full")
    return both.agg(F.max(F.abs(F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0)))).alias("e_inf"))


def order(df: DataFrame, by: list[str]) -> DataFrame:
    """``df(by.., n, error)``: log2 of successive error ratios, per doubling of n."""
    w = Window.partitionBy(*by).orderBy("n")
    before = F.lag("error").over(w)
    return df.withColumn("order", F.log2(before / F.col("error")) / F.log2(F.col("n") / F.lag("n").over(w)))


def order_fit(df: DataFrame, by: list[str]) -> DataFrame:
    """Slope of log error against log n, with its sign turned."""
    return df.groupBy(*by).agg((-F.regr_slope(F.log("error"), F.log("n"))).alias("order"))


def speedup(df: DataFrame, by: list[str]) -> DataFrame:
    """``df(by.., nodes, seconds)``: strong scaling against the fewest nodes; s = T0 / T1 and s / r."""
    w = Window.partitionBy(*by).orderBy("nodes")
    r = F.col("nodes") / F.first("nodes").over(w)
    s = F.first("seconds").over(w) / F.col("seconds")
    return df.withColumn("r", r).withColumn("speedup", s).withColumn("strong_efficiency", F.col("speedup") / F.col("r"))


def weak_efficiency(df: DataFrame, by: list[str]) -> DataFrame:
    w = Window.partitionBy(*by).orderBy("nodes")
    return df.withColumn("r", F.col("nodes") / F.first("nodes").over(w)).withColumn("efficiency", F.first("seconds").over(w) / F.col("seconds"))


def strong_efficiency(df: DataFrame, by: list[str]) -> DataFrame:
    return speedup(df, by)


def amdahl(alpha: Column | float, r: Column) -> Column:
    """Strong speedup of a parallel share alpha on r times the resources."""
    a = F.lit(alpha) if isinstance(alpha, float | int) else alpha
    return 1 / (a / r + 1 - a)


def gustafson(alpha: Column | float, r: Column) -> Column:
    """Weak efficiency of a parallel share alpha on r times the resources."""
    a = F.lit(alpha) if isinstance(alpha, float | int) else alpha
    return 1 / (a + r * (1 - a))


def fit_beta(df: DataFrame, by: list[str]) -> DataFrame:
    """Serial share from weak efficiencies: least squares of 1 / efficiency - 1 on r - 1 through the origin; null for a single r."""
    x, y = F.col("r") - 1, 1 / F.col("efficiency") - 1
    return df.groupBy(*by).agg(F.try_divide(F.sum(x * y), F.sum(x * x)).alias("beta"))


def throughput(unknowns: Column, seconds: Column, padded: Column | float = 1.0) -> Column:
    """MB (1e6 bytes) of unknowns per second, times the padding factor where transforms are padded."""
    return unknowns * 8 * (F.lit(padded) if isinstance(padded, float | int) else padded) / seconds / 1e6


def switch_cost(spark: SparkSession, w: Workers) -> DataFrame:
    """Blocks and bytes of each switch of a forward transform, and the send-side copies and rows of each strategy."""
    out = None
    for step, to in ((0, 1), (1, 2)):
        t = block_table(spark, w, step, to).agg(F.count("*").alias("blocks"), F.sum("bytes").alias("bytes"), F.max("bytes").alias("largest_block"))
        t = t.withColumn("switch", F.lit(step + 1))
        out = t if out is None else out.unionByName(t)
    kinds = spark.createDataFrame([("packed_barrier", 2.0, False), ("batched_async", 1.0, False), ("unpacked_direct", 1.0, True)], "strategy string, copies double, by_cell boolean")
    # six rows
    out = out.crossJoin(F.broadcast(kinds))
    rows = F.when(F.col("by_cell"), F.col("bytes") / 8).otherwise(F.col("blocks")).cast("long")
    return out.withColumn("rows", rows).withColumn("copied_bytes", F.col("copies") * F.col("bytes")).drop("by_cell", "copies")


def parseval(values: DataFrame, spectrum: DataFrame, plan: TransformPlan) -> DataFrame:
    """Energy of a fully periodic real field on both sides; half spectra count their inner modes twice."""
    n = 1
    for a in range(3):
        n *= plan.lines[a].intervals
    half = next(a for a in range(3) if not plan.lines[a].complex_in and plan.lines[a].kind[0] == "dft")
    k, m = F.col(("kx", "ky", "kz")[half]), plan.lines[half].intervals
    once = (k == 0) | ((k == m // 2) & F.lit(m % 2 == 0))
    e = spectrum.agg((F.sum((F.col("re") ** 2 + F.col("im") ** 2) * F.when(once, 1.0).otherwise(2.0)) / n).alias("spectral"))
    # one row on each side
    return values.agg(F.sum(F.col("v") ** 2).alias("direct")).crossJoin(e)


def timed(run, label: str, workers: int) -> dict:
    """Wall seconds of a full evaluation of a DataFrame, its rows counted by a sink that keeps nothing."""
    began = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return {"method": label, "workers": workers, "seconds": time.perf_counter() - began}


def phases(spark: SparkSession, run, label: str, workers: int) -> list[dict]:
    """Seconds per stage of a run, in order: each switch ends a stage, so a stage is one line pass with its pack and unpack."""
    group = f"phases-{label}-{time.time_ns()}"
    spark.sparkContext.setJobGroup(group, label)
    total = timed(run, label, workers)
    tracker = spark.sparkContext.statusTracker()
    stages = sorted({s for j in tracker.getJobIdsForGroup(group) for s in tracker.getJobInfo(j).stageIds})
    store = spark.sparkContext._jsc.sc().statusStore()
    rows = []
    for k, s in enumerate(stages):
        try:
            d = store.lastStageAttempt(s)
        except Exception as error:  # a skipped stage has no attempt
            if "NoSuchElement" not in str(error):
                raise
            continue
        if not d.numCompleteTasks():  # skipped: its shuffle files were there already
            continue
        rows.append({"method": label, "workers": workers, "phase": f"stage {k}", "seconds": d.executorRunTime() / 1000, "shuffle_read": d.shuffleReadBytes(), "shuffle_write": d.shuffleWriteBytes()})
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    return [*rows, {**total, "phase": "total", "shuffle_read": None, "shuffle_write": None}]


#: What a worker does in a line pass: its transforms; packing, pasting and clearing; and waiting for, or handing over, tiles.
PHASES = ("compute", "copy", "communication")


def breakdown(spark: SparkSession, run, label: str) -> DataFrame:
    """(strategy, line_pass, phase, seconds) of a solve, added up over its workers. ``run(clock)`` gives the solve with that clock in
    its options; line passes are numbered in the order in which they run. The first one takes in the caller's data.

    Spark separates stages, so copies overlap the communication of other workers, never that of the same switch's senders.
    """
    from .poisson import clocked

    clock = clocked(spark)
    run(clock).write.format("noop").mode("overwrite").save()
    passes = _in_order(list({k[:2] for k in clock.value}))
    rows = [(label, passes[step, done], phase, float(seconds)) for (step, done, phase), seconds in clock.value.items()]
    return spark.createDataFrame(rows, "strategy string, line_pass int, phase string, seconds double")


def _in_order(steps: list[tuple[int, bool]]) -> dict[tuple[int, bool], int]:
    """Forward passes by step, the way back from the last to the first."""
    there = sorted(k for k in steps if not k[1])
    back = sorted((k for k in steps if k[1]), reverse=True)
    return {k: i + 1 for i, k in enumerate([*there, *back])}


__all__ = [n for n in dir() if not n.startswith("_")] + ["padding_factor"]
