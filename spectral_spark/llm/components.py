"""Connected components of a link table by alternating star contraction, wholly in Spark.

Every round replaces each node's links by links to the least node it sees, from its greater and then its lesser
neighbours, until nothing changes; the number of rounds grows with the logarithm of the longest path. Minima per node are
combined before the shuffle, and joins leave the division of hot nodes to adaptive execution. Links never reach the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import drop, table


def _state(links: DataFrame) -> tuple:
    row = links.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return row[0], row[1]


def _star(spark: SparkSession, links: DataFrame, large: bool) -> tuple[DataFrame, DataFrame]:
    """u > v in ``links``. Large star: neighbours above u move to u's least one; small star: those below and u itself.

    Also returns the table of minima, which can go once the links are written. It is a table so that the join has an exchange on
    both sides, and the links of a hub can be divided.
    """
    if large:
        near = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        near = links
    least = table(spark, near.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), "least")
    joined = near.join(least, "u")
    if large:
        out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
    return out.where("u > v").distinct(), least


def components(spark: SparkSession, links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``links(a, b)`` of longs to ``(id, component)``: the least id reachable, for every id that has a link.

    Null ends, loops and repeats are ignored; an empty table gives an empty result.
    """
    now = table(spark, links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "links")
    state = _state(now)
    for _ in range(max_rounds):
        if not state[0]:
            break
        large, above = _star(spark, now, True)
        half = table(spark, large, "links")
        small, below = _star(spark, half, False)
        then = table(spark, small, "links")
        drop(spark, now, above, half, below)
        now, before, state = then, state, _state(then)
        if state == before:
            break
    else:
        raise RuntimeError("components did not settle")
    ends = now.select(F.col("u").alias("id"), F.col("v").alias("component"))
    ends = ends.unionByName(now.select(F.col("v").alias("id"), F.col("v").alias("component")))
    return ends.groupBy("id").agg(F.min("component").alias("component"))
