"""Which worker owns which index: three distributions, with owners and starts in constant time."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Distribution:
    """``n`` indices over ``p`` workers.

    - ``first_heavy``: the first n mod p workers hold one index more.
    - ``proportional``: worker r starts at floor(r n / p); its owner function needs a search.
    - ``strided``: the excess indices go to every (p div (n mod p))-th worker, so that neighbours, who share a machine, share
      the load; start and owner are both closed forms.
    """

    n: int
    p: int
    kind: str = "strided"

    def __post_init__(self):
        if self.p < 1 or self.n < 0 or self.kind not in ("first_heavy", "proportional", "strided"):
            raise ValueError(f"not a distribution: {self}")

    @property
    def base(self) -> int:
        return self.n // self.p

    @property
    def excess(self) -> int:
        return self.n % self.p

    @property
    def stride(self) -> int:
        return self.p // self.excess if self.excess else self.p

    @property
    def degenerate(self) -> bool:
        """The strided form equals first_heavy: no excess, or excess for more than half of the workers."""
        return self.excess == 0 or self.stride == 1

    def starts(self) -> np.ndarray:
        """First index of every worker, and n."""
        r = np.arange(self.p + 1)
        if self.kind == "proportional":
            return r * self.n // self.p
        if self.kind == "first_heavy" or not self.excess:
            return r * self.base + np.minimum(r, self.excess)
        return r * self.base + np.minimum(r // self.stride, self.excess) if self.p else r

    def owners(self) -> np.ndarray:
        return np.repeat(np.arange(self.p), np.diff(self.starts()))

    def start(self, r: Column) -> Column:
        if self.kind == "proportional":
            return F.floor(r * F.lit(self.n) / F.lit(self.p)).cast("long")
        every = self.stride if self.kind == "strided" and self.excess else 1
        return (r * self.base + F.least(F.floor(r / every), F.lit(self.excess))).cast("long")

    def owner(self, i: Column) -> Column:
        """Owner of an index column, in integer arithmetic."""
        whole = lambda a, b: F.floor(a / b)
        i = i.cast("long")
        if self.kind == "proportional":
            # the least r with start(r + 1) > i
            return (F.ceil((i + 1) * F.lit(self.p) / F.lit(max(self.n, 1))) - 1).cast("int")
        s = self.stride if self.kind == "strided" and self.excess else 1
        if not self.excess:
            return whole(i, max(self.base, 1)).cast("int")
        group = s * self.base + 1
        g = whole(i, group)
        within = i - g * group
        inside = g * s + (F.least(whole(within, self.base), F.lit(s - 1)) if self.base else F.lit(s - 1))
        if not self.base:
            return inside.cast("int")
        rest = whole(i - self.excess * group, self.base) + self.excess * s
        return F.when(g < self.excess, inside).otherwise(rest).cast("int")

    def table(self, spark: SparkSession) -> DataFrame:
        """(worker, first, after): a row per worker, for joins by range."""
        return spark.range(self.p).select(F.col("id").cast("int").alias("worker"), self.start(F.col("id")).alias("first"), self.start(F.col("id") + 1).alias("after"))


def first_heavy(n: int, p: int) -> Distribution:
    return Distribution(n, p, "first_heavy")


def proportional(n: int, p: int) -> Distribution:
    return Distribution(n, p, "proportional")


def strided(n: int, p: int) -> Distribution:
    return Distribution(n, p, "strided")


def is_degenerate(n: int, p: int) -> bool:
    return strided(n, p).degenerate


def balance(df: DataFrame, worker: str, weight: Column, workers_per_node: int) -> DataFrame:
    """Load per worker and per node (group of consecutive workers), with the spread over all."""
    load = df.groupBy(F.col(worker).alias("worker")).agg(F.sum(weight).alias("load")).withColumn("node", F.floor(F.col("worker") / workers_per_node).cast("int"))
    return load.groupBy("node").agg(F.sum("load").alias("node_load"), F.max("load").alias("max_worker"), F.min("load").alias("min_worker"))
