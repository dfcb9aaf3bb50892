"""Corpus pipeline: toxicity, near-duplicates, repeated passages, source mixture, packing.

Every stage works on all that the one before kept. ``run`` writes each stage's rows to the shared folder and reads them
again, so a lost executor costs at most the running stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spectral_spark.llm.mixing import mix_sources
from spectral_spark.llm.near_dedup import MinHash, drop_copies
from spectral_spark.llm.packing import pack
from spectral_spark.llm.store import table
from spectral_spark.llm.substring_dedup import dedup_substrings
from spectral_spark.llm.toxicity import fit_toxicity, score_toxicity

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier chain does not reject."""
    chain = fit_toxicity(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score_toxicity(spark, docs.select(*COLUMNS), chain).where("not rejected").select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The row of least id of each group; shingles of five words, similarity 0.8."""
    return drop_copies(spark, docs.select(*COLUMNS), MinHash(words=5, percent=80)).select(*COLUMNS)


def cut_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages stay where they stand first and are cut from all other texts."""
    out = dedup_substrings(spark, docs.select(*COLUMNS))
    cut = F.col("n_removed") > 0
    size = F.when(cut, F.length("clean_text").cast("long")).otherwise(F.col("n_chars"))
    return out.withColumn("n_chars", size).withColumn("text", F.col("clean_text")).select(*COLUMNS)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mixture takes it."""
    out = mix_sources(docs.select(*COLUMNS)).where("copies > 0")
    return out.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select(*COLUMNS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(spark, docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_dedup", drop_near_duplicates),
    ("substring_dedup", cut_repeated_passages),
    ("mixing", mix),
    ("packing", pack_sequences),
]

#: A trained classifier and MinHash components have no SQL form; tests/llm compare every stage with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = table(spark, docs, f"stage_{name}")
    return docs
