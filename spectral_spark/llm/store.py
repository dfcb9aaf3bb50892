"""Cutting lineage through tables in the shared checkpoint folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder. Where none is set, a folder of our own, on a single machine only (tests)."""
    path = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if path is None:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        path = getattr(shared_dir, "own", None) or tempfile.mkdtemp(prefix="spark_shared_")
        shared_dir.own = path
    return path.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/llm_work/{name}-{uuid.uuid4().hex}"


#: Rows that go to a Python worker at a time: texts can be long, and both sides hold a batch more than once.
BATCH_ROWS = 1000
BATCH_CONF = "spark.sql.execution.arrow.maxRecordsPerBatch"


def table(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: later stages survive a lost executor."""
    path = fresh_path(spark, name)
    before = int(spark.conf.get(BATCH_CONF))
    spark.conf.set(BATCH_CONF, min(before, BATCH_ROWS) if before > 0 else BATCH_ROWS)
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(BATCH_CONF, before)
    out = spark.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def drop(spark: SparkSession, *frames: DataFrame | None) -> None:
    """Delete tables made by :func:`table` that nothing will read again."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for df in frames:
        path = getattr(df, "stored_at", None)
        if path:
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(conf).delete(p, True)
