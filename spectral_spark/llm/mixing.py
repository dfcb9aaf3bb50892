"""Mixing sources to target weights, in DataFrame operations only.

Words are added up per source; each source's share of the total, capped at a multiple of what it has, gives its rate; a document
is taken floor(rate) times, and once more with the fraction's probability, drawn from a hash of its id, text and source.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .store import table

#: Most sources whose targets are broadcast, and most bytes of their names.
BROADCAST_SOURCES, BROADCAST_BYTES = 10_000, 1 << 20
WORD = r"[^\x20\x09-\x0D]+"


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (3, 1, 2), percent: int = 150, most: int = 2) -> DataFrame:
    """(source, source_size) to (source, source_size, target).

    Water filling: with caps of ``most`` times the size, the level L at which the sum of min(cap, weight * L) is the total is
    found from running sums in the order of cap per weight. There is one row per source, which is what bounds these windows.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    w = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1).cast("int"))
    s = sizes.withColumn("weight", w.cast("double")).withColumn("cap", (F.col("source_size") * most).cast("double"))
    everything = Window.partitionBy()
    rising = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    upto = rising.rowsBetween(Window.unboundedPreceding, -1)
    s = s.withColumn("total", F.sum("source_size").over(everything) * percent / 100.0).withColumn("all_weight", F.sum("weight").over(everything))
    s = s.withColumn("below", F.coalesce(F.sum("cap").over(upto), F.lit(0.0))).withColumn("weight_below", F.coalesce(F.sum("weight").over(upto), F.lit(0.0)))
    # the level if this source and all that fill later are not capped
    s = s.withColumn("level", (F.col("total") - F.col("below")) / (F.col("all_weight") - F.col("weight_below")))
    # the first source in that order whose share stays below its cap fixes the level
    first = F.min(F.when(F.col("weight") * F.col("level") <= F.col("cap"), F.struct("weight_below", "level"))).over(everything)
    s = s.withColumn("at", first["level"])
    return s.select("source", "source_size", F.when(F.col("at").isNull(), F.col("cap")).otherwise(F.least(F.col("cap"), F.col("weight") * F.col("at"))).alias("target"))


def draw(doc_id, text, source, seed: str):
    """A number in [0, 1) from a row's id, text and source; SQL engines without Spark's hashes can repeat it."""
    part = lambda c: F.coalesce(F.md5(c.cast("binary")), F.lit(""))
    key = F.concat_ws(":", F.lit(seed), F.coalesce(doc_id.cast("string"), F.lit("")), part(text), part(source))
    return F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def mix_sources(docs: DataFrame, weights: tuple[int, ...] = (3, 1, 2), percent: int = 150, most: int = 2, seed: str = "mix") -> DataFrame:
    """The documents with size, source_size, target and copies (how often each is taken).

    A null text has size 0; null is a source of its own, the last. Each row draws by its id, text and source: rows that share an
    id, also a null one, draw apart, and only rows that repeat all three draw alike. A source without words gets no copies. Sources
    are counted at once, and joined by null-safe equality. Other columns stay, whatever their names; those of the result are replaced.
    """
    own = ["size", "source_size", "target", "copies"]
    size = F.coalesce(F.regexp_count(F.col("text").cast("string"), F.lit(WORD)), F.lit(0)).cast("long")
    # struct columns keep the joined sides' names apart from any of the caller's
    number = draw(F.col("doc_id"), F.col("text"), F.col("source"), seed)
    rows = docs.drop(*own).select(F.struct("*").alias("row"), size.alias("size"), number.alias("number"), F.col("source").cast("string").alias("key"))
    spark = docs.sparkSession
    sizes = table(spark, rows.groupBy(F.col("key").alias("source")).agg(F.sum("size").alias("source_size")), "sources")
    mixture = source_targets(sizes, weights, percent, most).select(F.col("source").alias("of"), "source_size", "target")
    # one row a source: so few are sent to all tasks, and no text is moved; more are joined by a shuffle, which can be divided
    n, names = sizes.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("source")), F.lit(0))).first()
    if n <= BROADCAST_SOURCES and names <= BROADCAST_BYTES:
        mixture = F.broadcast(mixture)
    out = rows.join(mixture, F.col("key").eqNullSafe(F.col("of")))
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    more = (F.col("number") < rate - F.floor(rate)).cast("long")
    copies = F.least(F.floor(rate).cast("long") + more, F.lit(most).cast("long"))
    return out.select("row.*", "size", "source_size", "target", copies.alias("copies"))


SQL = r"""
WITH d AS (SELECT doc_id, source, text, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents),
s0 AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
s AS (SELECT source, source_size, CAST([3, 1, 2][CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS INT)] AS DOUBLE) AS weight, CAST(source_size * 2 AS DOUBLE) AS cap FROM s0),
r AS (SELECT *, (SELECT sum(source_size) * 150 / 100.0 FROM s) AS total, (SELECT sum(weight) FROM s) AS all_weight,
        coalesce(sum(cap) OVER w, 0.0) AS below, coalesce(sum(weight) OVER w, 0.0) AS weight_below
      FROM s WINDOW w AS (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
l AS (SELECT *, (total - below) / (all_weight - weight_below) AS level FROM r),
f AS (SELECT level AS open_level FROM l WHERE weight * level <= cap ORDER BY weight_below LIMIT 1),
t AS (SELECT source, source_size, least(cap, coalesce(weight * (SELECT open_level FROM f), cap)) AS target FROM l),
j AS (SELECT d.doc_id, d.text, d.source, d.size, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0.0 END AS rate
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
  size * least(CAST(floor(rate) AS BIGINT) + CASE WHEN CAST(('0x' || substr(md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), '') || ':' || coalesce(md5(text), '') || ':' || coalesce(md5(source), '')), 1, 8)) AS BIGINT) / 4294967296.0 < rate - floor(rate) THEN 1 ELSE 0 END, 2) AS taken
FROM j
"""
