"""Fields from tables: declared binnings, dense grids, sinks, and a Python data source for analytic fields."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import DoubleType, IntegerType

#: Forms of a field, as in the fixtures.
CELL_SCHEMA = {"ix": IntegerType(), "iy": IntegerType(), "iz": IntegerType(), "v": DoubleType()}


def check_field_schema(df: DataFrame) -> DataFrame:
    have = {f.name: f.dataType for f in df.schema}
    wrong = [c for c, t in CELL_SCHEMA.items() if have.get(c) != t]
    if wrong:
        raise TypeError(f"a cell table needs {CELL_SCHEMA}; wrong: {wrong}")
    return df


def rasterise(df: DataFrame, ix: Column, iy: Column, iz: Column, value: Column, comp: Column | None = None) -> DataFrame:
    """Rows to cells, by partial and final sums; filters and column choices before it reach the scan."""
    keys = [ix.cast("int").alias("ix"), iy.cast("int").alias("iy"), iz.cast("int").alias("iz")]
    if comp is not None:
        keys.append(comp.cast("int").alias("comp"))
    return df.groupBy(*keys).agg(F.sum(value.cast("double")).alias("v"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def day(column: str, start: str) -> Column:
    return F.datediff(F.col(column), F.lit(start).cast("date"))


def cube_lineitem(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """Part x supplier x ship day, revenue in millions."""
    t = table(spark, sf_dir, "lineitem").where(F.col("l_shipdate").isNotNull())
    return rasterise(t, F.pmod("l_partkey", F.lit(n)), F.pmod("l_suppkey", F.lit(n)), F.pmod(day("l_shipdate", "1995-01-01"), F.lit(n)), F.col("l_extendedprice") * (1 - F.col("l_discount")) / 1e6)


def cube_events(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """Day x hour x property k, values in thousands."""
    t = table(spark, sf_dir, "events")
    return rasterise(t, F.floor(day("ts", "2024-01-01") * n / 30), F.floor(F.hour("ts") * n / 24), F.pmod(F.get_json_object("props", "$.k").cast("int"), F.lit(n)), F.col("value") / 1e3)


def cube_orders(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """Day x customer x order number, prices in millions."""
    t = table(spark, sf_dir, "orders")
    return rasterise(t, F.pmod(day("o_orderdate", "1995-01-01"), F.lit(n)), F.pmod("o_custkey", F.lit(n)), F.pmod("o_orderkey", F.lit(n)), F.col("o_totalprice") / 1e6)


def components_lineitem(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """Three measures of a line item as the components of a vector field."""
    t = table(spark, sf_dir, "lineitem")
    price = F.col("l_extendedprice") / 1e6
    parts = F.posexplode(F.array(price * F.col("l_tax"), price * F.col("l_discount"), price)).alias("comp", "part")
    t = t.select("l_partkey", "l_suppkey", "l_shipdate", parts)
    return rasterise(t, F.pmod("l_partkey", F.lit(n)), F.pmod("l_suppkey", F.lit(n)), F.pmod(day("l_shipdate", "1995-01-01"), F.lit(n)), F.col("part"), F.col("comp"))


def dense(spark: SparkSession, cells: DataFrame, n: int) -> DataFrame:
    """Every cell of an n^3 grid, missing ones zero, by a left join from the index."""
    i = F.col("id")
    index = spark.range(n**3).select(F.floor(i / (n * n)).cast("int").alias("ix"), (F.floor(i / n) % n).cast("int").alias("iy"), (i % n).cast("int").alias("iz"))
    return index.join(cells, ["ix", "iy", "iz"], "left").withColumn("v", F.coalesce("v", F.lit(0.0)))


def lines(cells: DataFrame, key: str, n: int, index: str = "j", value: str = "v") -> DataFrame:
    """(key, line): one array per key over 0..n-1, missing points zero; a point beyond the line, or without an index, is an error."""
    at = F.col(index)
    error = F.raise_error(F.concat(F.lit("point outside the line: "), F.coalesce(at.cast("string"), F.lit("null"))))
    got = cells.withColumn(index, F.when(at.isNotNull() & at.between(0, n - 1), at).otherwise(error.cast("int")))
    got = got.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct(F.col(index).cast("int"), F.col(value)))).alias("m"))
    return got.select(key, F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda j: F.coalesce(F.col("m")[j], F.lit(0.0))).alias("line"))


def write_slabs(cells: DataFrame, path: str, slab: int = 1) -> None:
    """Parquet partitioned by slab number, so that a sub-box reads its slabs only."""
    cells.withColumn("slab", F.floor(F.col("ix") / slab).cast("int")).write.mode("overwrite").partitionBy("slab").parquet(path)


class _Slab(InputPartition):
    def __init__(self, x: int):
        self.x = x


class GridSource(DataSource):
    """``spark.read.format("grid").option("case", ...).option("n", ...)``: right-hand side of an analytic case, a partition per slab."""

    @classmethod
    def name(cls) -> str:
        return "grid"

    def schema(self) -> str:
        return "ix int, iy int, iz int, v double"

    def reader(self, schema) -> DataSourceReader:
        return _GridReader(self.options.get("case", "spectral"), int(self.options.get("n", "8")))


class _GridReader(DataSourceReader):
    def __init__(self, case: str, n: int):
        self.case, self.n = case, n

    def partitions(self):
        from .analytic import case_grid

        return [_Slab(x) for x in range(case_grid(self.case, self.n).shape[0])]

    def read(self, partition):
        from .analytic import CASES, _line, case_grid

        spec = case_grid(self.case, self.n)
        (x, xx), (y, yy), (z, zz) = (_line(kind, a.coordinates()) for kind, a in zip(CASES[self.case][0], spec.axes))
        i = partition.x
        f = xx[i] * np.outer(y, z) + x[i] * np.outer(yy, z) + x[i] * np.outer(y, zz)
        for (j, k), v in np.ndenumerate(f):
            yield i, j, k, float(v)
