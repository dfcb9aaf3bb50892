"""Substring deduplication: paragraphs that repeat across documents, found by MinHash banding and cut to their borders.

Passages are repeated inside lines as well as between them, so every run of 25 successive words is a paragraph. A paragraph's MinHash
is taken over its 21 shingles of five words; the least shingles of ``rows`` hash functions make a band's key, and a key is noted once
for all successive paragraphs that have it. With two bands of one row, paragraphs similar at 80 % share a key with probability
0.96, equal ones always. A passage of 50 words or more whose copy is similar at 80 % holds an equal paragraph, so it always collides.

Colliding paragraphs are verified word by word. Of every ``span`` successive windows of ``size`` words the one whose first words hash
least is a seed (all of them on a tie); every paragraph holds one, and equal paragraphs the same one. A seed's key is the hash of all
its words, so places of a key are equal and need no comparison with each other; a place whose key stands in an earlier document
repeats it. Where a chain of repeating seeds begins or ends, the windows at every word of the next ``span - 1`` are looked up in the same
way: a run of 25 or more words that an earlier document has is thereby found to its first and last word.

Runs are removed whose paragraphs reach the exact Jaccard similarity by them alone: 19 of 21 shingles, which is 23 words. A shorter
text keeps all. Two runs with the same home are removed with the words between them where the whole is
similar by edit distance (``percent``). Removals are clustered: a run and the place that it repeats are linked, overlapping places of a
document are one, and of each component the passage stays in the first document.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

from .components import components
from .store import BATCH_ROWS, drop, table
from .words import BASE, LOWER, Block, mix, text_blocks, tidy


@dataclass(frozen=True)
class Paragraphs:
    """``size`` and ``span`` of the verifying windows; a paragraph has ``size + span - 1`` words, its shingles ``words``."""

    size: int = 16
    span: int = 10
    words: int = 5
    percent: int = 80
    bands: int = 2
    rows: int = 1

    def __post_init__(self):
        # a span that begins in a text must not reach the next text's windows
        assert self.span <= self.size and self.words <= self.size

    @property
    def shingles(self) -> int:
        """Of a paragraph."""
        return self.size + self.span - self.words

    @property
    def least_run(self) -> int:
        """Words of the shortest equal run by which two paragraphs reach the similarity: s common shingles of n each are similar at
        s / (2 n - s)."""
        return -(-2 * self.percent * self.shingles // (100 + self.percent)) + self.words - 1


SEEDS = "key long, doc_id long, row long, first int, again boolean"
MOST = np.uint64(0xFFFFFFFFFFFFFFFF)
FACTOR = np.uint64(0xD6E8FEB86659FD93)


def window_keys(word: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
    """Hash of the ``size`` words from each place."""
    key, base = np.zeros(len(at), np.uint64), np.uint64(1)
    with np.errstate(over="ignore"):
        for k in range(size):
            key += word[at + k] * base
            base *= BASE
    return mix(key, 5).view(np.int64)


def shingle_hashes(word: np.ndarray, size: int) -> np.ndarray:
    """Of the ``size`` words from each place; the last places run out of words."""
    out, n = np.zeros(len(word), np.uint64), len(word)
    for k in range(min(size, n)):
        out[: n - k] = out[: n - k] * FACTOR + word[k:]
    return out


def sliding_least(x: np.ndarray, span: int) -> np.ndarray:
    """Least of the ``span`` values from each place (of fewer at the end), by doubling."""
    out, have = x.copy(), 1
    while have < min(span, len(x)):
        step = min(have, span - have, len(x) - have)
        np.minimum(out[: len(x) - step], out[step:].copy(), out=out[: len(x) - step])
        have += step
    return out


def band_runs(block: Block, word: np.ndarray, p: Paragraphs) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, key, first paragraph, last paragraph) of every run of successive paragraphs that have a band's key.

    A paragraph is named by the place in ``word`` where it begins. A text shorter than a paragraph is one.
    """
    count = block.counts
    made = np.maximum(count - p.words + 1, 0)
    # paragraphs of a text; none if it has not even one window
    starts = np.where(count < p.size, 0, np.maximum(made - p.shingles + 1, 1))
    long, short = np.flatnonzero(made >= p.shingles), np.flatnonzero((starts == 1) & (made < p.shingles))
    base = shingle_hashes(word, p.words)
    text = np.repeat(np.arange(len(count)), starts)
    place = np.arange(len(text)) + np.repeat(block.first[:-1] - np.concatenate([[0], np.cumsum(starts)[:-1]]), starts)
    new = np.ones(len(text), bool)
    out = []
    for band in range(p.bands):
        key = np.full(len(word), band + 1, np.uint64)
        for row in range(p.rows):
            order = mix(base, 40 + band * p.rows + row)
            least = sliding_least(order, p.shingles)
            for t in short:
                least[block.first[t]] = order[block.first[t] : block.first[t] + made[t]].min()
            key = mix(key * FACTOR + least, 3)
        key = key[place]
        new[1:] = (key[1:] != key[:-1]) | (text[1:] != text[:-1])
        at = np.flatnonzero(new)
        last = np.append(at[1:], len(text)) - 1 if len(at) else at
        out.append((text[at], key[at].view(np.int64), place[at], place[last]))
    assert len(long) + len(short) == (starts > 0).sum()
    return tuple(np.concatenate(x) for x in zip(*out))


def named(docs: DataFrame) -> DataFrame:
    """doc_id, text and ``row``, by which rows that share an id are told apart; rows without an id or a text are left out."""
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return own.where("doc_id is not null and text is not null").withColumn("row", F.xxhash64("doc_id", "text"))


def band_rows(docs: DataFrame, p: Paragraphs) -> DataFrame:
    """(key, doc_id, row): every band key that a text's paragraphs have, once a text."""

    def run(batches):
        for batch in batches:
            for i, j, data, at in text_blocks(batch.column("text")):
                block = Block(data, at)
                text, key, _, _ = band_runs(block, block.hashes(LOWER), p)
                order = np.lexsort((key, text))
                text, key = text[order], key[order]
                new = np.ones(len(key), bool)
                new[1:] = (key[1:] != key[:-1]) | (text[1:] != text[:-1])
                owner = pa.array(text[new])
                part = batch.slice(i, j - i)
                columns = [pa.array(key[new]), *(part.column(c).take(owner) for c in ("doc_id", "row"))]
                yield pa.RecordBatch.from_arrays(columns, ["key", "doc_id", "row"])

    return docs.mapInArrow(tidy(run), "key long, doc_id long, row long")


def seeds(block: Block, word: np.ndarray, p: Paragraphs) -> tuple[np.ndarray, np.ndarray]:
    """(text, place in ``word``) of every seed."""
    n, count = len(word), block.counts
    made = np.maximum(count - p.size + 1, 0)
    if not made.any():
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    order = np.maximum(mix(shingle_hashes(word, p.words), 9), np.uint64(1))
    text = np.repeat(np.arange(len(count)), count)
    place = np.arange(n) - block.first[text]
    order[place >= made[text]] = MOST
    least = order.copy()
    for k in range(1, p.span):
        np.minimum(least[: n - k], order[k:], out=least[: n - k])
    # only spans that lie in the text's windows, or all of these where they are fewer
    least[place >= np.maximum(made - p.span + 1, np.minimum(made, 1))[text]] = 0
    chosen = least.copy()
    for k in range(1, p.span):
        np.maximum(chosen[k:], least[: n - k], out=chosen[k:])
    at = np.flatnonzero((chosen == order) & (place < made[text]))
    return text[at], at


def _again(text: np.ndarray, key: np.ndarray) -> np.ndarray:
    """Whether a text has the key at an earlier place (places ascend)."""
    sort = np.lexsort((key, text))
    out = np.zeros(len(key), bool)
    out[sort[1:]] = (key[sort][1:] == key[sort][:-1]) & (text[sort][1:] == text[sort][:-1])
    return out


def _rows(part: pa.RecordBatch, block: Block, word: np.ndarray, text: np.ndarray, at: np.ndarray, p: Paragraphs) -> pa.RecordBatch:
    key = window_keys(word, at, p.size)
    first = (at - block.first[text]).astype(np.int32)
    owner = pa.array(text)
    columns = [pa.array(key), *(part.column(c).take(owner) for c in ("doc_id", "row")), pa.array(first), pa.array(_again(text, key))]
    return pa.RecordBatch.from_arrays(columns, ["key", "doc_id", "row", "first", "again"])


def seed_rows(docs: DataFrame, asked: DataFrame, p: Paragraphs) -> DataFrame:
    """The seeds that lie in a paragraph with one of the keys of ``asked(doc_id, row, keys)``: key, doc_id, row, first word, and whether the
    text has the key before."""

    def run(batches):
        for batch in batches:
            for i, j, data, at in text_blocks(batch.column("text")):
                block, part = Block(data, at), batch.slice(i, j - i)
                word = block.hashes(LOWER)
                lists = part.column("keys")
                owner = np.repeat(np.arange(j - i), np.diff(lists.offsets.to_numpy()))
                text, key, lo, hi = band_runs(block, word, p)
                name = lambda t, k: mix(k.view(np.uint64) * FACTOR + t.astype(np.uint64))
                hit = np.isin(name(text, key), name(owner, lists.flatten().to_numpy()))
                # windows that begin in a colliding paragraph and end in it
                inside = np.zeros(len(word) + p.span + 1, np.int64)
                np.add.at(inside, lo[hit], 1)
                np.add.at(inside, hi[hit] + p.span, -1)
                text, at_ = seeds(block, word, p)
                keep = np.cumsum(inside)[at_] > 0
                yield _rows(part, block, word, text[keep], at_[keep], p)

    return docs.join(asked, ["doc_id", "row"]).select("doc_id", "row", "text", "keys").mapInArrow(tidy(run), SEEDS)


def border_rows(docs: DataFrame, borders: DataFrame, p: Paragraphs) -> DataFrame:
    """The windows at every word of the ``span - 1`` before or after the seeds of ``borders(doc_id, row, borders)``, like :func:`seed_rows`.

    A border is twice the seed's first word, plus one for the words after it."""

    def run(batches):
        for batch in batches:
            for i, j, data, limits in text_blocks(batch.column("text")):
                block, part = Block(data, limits), batch.slice(i, j - i)
                word = block.hashes(LOWER)
                lists = part.column("borders")
                text = np.repeat(np.arange(j - i), np.diff(lists.offsets.to_numpy()))
                asked = lists.flatten().to_numpy()
                step = np.arange(1, p.span)
                place = ((asked >> 1)[:, None] + np.where(asked & 1, 1, -1)[:, None] * step).ravel()
                text = np.repeat(text, len(step))
                good = (place >= 0) & (place <= block.counts[text] - p.size)
                at = np.unique(block.first[text[good]] + place[good])
                yield _rows(part, block, word, np.searchsorted(block.first, at, "right") - 1, at, p)

    return docs.join(borders, ["doc_id", "row"]).select("doc_id", "row", "text", "borders").mapInArrow(tidy(run), SEEDS)


def colliding(spark: SparkSession, docs: DataFrame, p: Paragraphs) -> DataFrame:
    """(doc_id, row, keys): of each text, the band keys that other texts have as well."""
    bands = table(spark, band_rows(docs, p), "bands")
    several = table(spark, bands.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"), "band_keys")
    # tables on both sides: a key that very many paragraphs share can be divided
    asked = table(spark, bands.join(several, "key").groupBy("doc_id", "row").agg(F.collect_list("key").alias("keys")), "colliding")
    drop(spark, bands, several)
    return asked


def _shared(spark: SparkSession, rows: DataFrame, name: str) -> DataFrame:
    """The rows whose key stands in several documents, with the first of these (``home``) and the key's place there (``at``)."""
    # keys are few here; a key of rows that repeat one doc_id passes and fails below
    # tables, so that the joins below have an exchange on both sides and a key of very many places can be divided
    several = table(spark, rows.where("not again").groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"), f"{name}_keys")
    some = table(spark, rows.join(several, "key"), f"{name}_some")
    place = F.min_by("first", F.when(~F.col("again"), F.struct("doc_id", "first")))
    homes = some.groupBy("key").agg(F.min("doc_id").alias("home"), F.max("doc_id").alias("hi"), place.alias("at")).where("home < hi")
    homes = table(spark, homes.drop("hi"), f"{name}_homes")
    out = table(spark, some.join(homes, "key").select("key", "doc_id", "row", "first", "home", "at"), name)
    drop(spark, several, some, homes)
    return out


def runs_of(text: np.ndarray, first: np.ndarray, home: np.ndarray, at: np.ndarray, p: Paragraphs) -> list[tuple]:
    """Runs of words to remove, of repeated windows (first, home, at) of several texts: (text, first, size, home and place there of the
    first word, and of the last)."""
    if not len(first):
        return []
    order = np.lexsort((at, home, first, text))
    text, first, home, shift = text[order], first[order], home[order], (at - first)[order]
    new = np.ones(len(first), bool)
    new[1:] = (text[1:] != text[:-1]) | (first[1:] > first[:-1] + p.size)
    begin = np.flatnonzero(new)
    end = np.append(begin[1:], len(first)) - 1
    # the window that ends a run, the first of equal ones, says where its end lies at home
    step = np.ones(len(first), bool)
    step[1:] = (first[1:] != first[:-1]) | new[1:]
    end = np.maximum.accumulate(np.where(step, np.arange(len(first)), 0))[end]
    long = first[end] + p.size - first[begin] >= p.least_run
    begin, end = begin[long], end[long]
    columns = (text[begin], first[begin], first[end] + p.size, home[begin], shift[begin], home[end], shift[end])
    out: list[list[int]] = []
    for run in zip(*(c.tolist() for c in columns)):
        t, a, b, _, shift_, home_, _ = run
        if out and out[-1][0] == t and out[-1][5] == run[3]:
            last = out[-1]
            here, there = a - last[2], a + shift_ - last[2] - last[6]
            changed = last[7] + max(here, there)
            if there >= 0 and 100 * changed <= (100 - p.percent) * (b - last[1]):
                last[2], last[5:] = b, [home_, run[6], changed]
                continue
        out.append([*run, 0])
    return [(r[0], r[1], r[2] - r[1], r[3], r[1] + r[4], r[5], r[2] - 1 + r[6]) for r in out]


RUNS = "doc_id long, row long, first long, size long, home long, home_first long, other long, other_last long"


def repeated_runs(spark: SparkSession, own: DataFrame, p: Paragraphs) -> DataFrame:
    """The runs of words that an earlier document has, of ``own(doc_id, row, text)``."""
    asked = colliding(spark, own, p)
    every = table(spark, seed_rows(own, asked, p), "seeds")
    seen = _shared(spark, every, "seen")
    drop(spark, every, asked)
    later = seen.where("doc_id > home")
    # seeds at which a chain of repeats begins or ends
    order = Window.partitionBy("doc_id", "row").orderBy("first")
    near = lambda c: F.coalesce(c <= p.size, F.lit(False))
    ends = later.select("key", near(F.col("first") - F.lag("first").over(order)).alias("l"), near(F.lead("first").over(order) - F.col("first")).alias("r"))
    ends = ends.where("not (l and r)").groupBy("key").agg(F.min("l").alias("l"), F.min("r").alias("r"))
    ends = table(spark, ends, "ends")
    sides = F.array(F.when(~F.col("l"), 2 * F.col("first")), F.when(~F.col("r"), 2 * F.col("first") + 1))
    asked = seen.join(ends, "key").select("doc_id", "row", F.explode(F.array_compact(sides)).alias("b"))
    borders = asked.groupBy("doc_id", "row").agg(F.collect_set("b").alias("borders"))
    fringe = table(spark, border_rows(own, borders, p), "fringe")
    found = _shared(spark, fringe, "borders")
    drop(spark, fringe, ends)
    window = F.struct("first", "home", "at")
    parts = later.unionByName(found.where("doc_id > home")).groupBy("doc_id", "row").agg(F.collect_list(window).alias("parts"))

    def merge(batches):
        for batch in batches:
            lists = batch.column("parts")
            owner = np.repeat(np.arange(batch.num_rows), np.diff(lists.offsets.to_numpy()))
            flat = lists.flatten()
            found = runs_of(owner, *(flat.field(c).to_numpy().astype(np.int64) for c in ("first", "home", "at")), p)
            texts, *columns = list(zip(*found)) or [()] * 7
            names = [batch.column(c).take(pa.array(texts, pa.int64())) for c in ("doc_id", "row")]
            yield pa.RecordBatch.from_arrays([*names, *(pa.array(c, pa.int64()) for c in columns)], [c.split()[0] for c in RUNS.split(", ")])

    runs = table(spark, parts.mapInArrow(tidy(merge), RUNS), "runs")
    drop(spark, seen, found)
    return runs


def clusters(spark: SparkSession, runs: DataFrame) -> DataFrame:
    """``runs`` with ``kept_in``: the first document of the component that a run belongs to.

    Nodes are stretches of a document that removed runs and the places they repeat cover together; a run links its own stretch with
    those of its first and its last word's home.
    """
    last = F.col("first") + F.col("size")
    spans = runs.select("doc_id", F.col("first").alias("a"), last.alias("b"))
    for home, lo, hi in (("home", F.col("home_first"), F.col("home_first") + 1), ("other", F.col("other_last"), F.col("other_last") + 1)):
        spans = spans.unionByName(runs.select(F.col(home).alias("doc_id"), lo.alias("a"), hi.alias("b")))
    spans = spans.groupBy("doc_id", "a").agg(F.max("b").alias("b"))
    order = Window.partitionBy("doc_id").orderBy("a")
    before = F.max("b").over(order.rowsBetween(Window.unboundedPreceding, -1))
    spans = spans.withColumn("new", F.when(before.isNull() | (F.col("a") >= before), F.col("a")))
    spans = spans.select("doc_id", "a", F.xxhash64("doc_id", F.max("new").over(order.rowsBetween(Window.unboundedPreceding, 0))).alias("node"))
    nodes = table(spark, spans, "stretches")
    at = lambda doc, a, name: nodes.select(F.col("doc_id").alias(doc), F.col("a").alias(a), F.col("node").alias(name))
    placed = runs.join(at("doc_id", "first", "mine"), ["doc_id", "first"])
    placed = placed.join(at("home", "home_first", "one"), ["home", "home_first"]).join(at("other", "other_last", "two"), ["other", "other_last"])
    placed = table(spark, placed.select("doc_id", "row", "first", "size", "mine", "one", "two"), "placed")
    links = placed.select(F.col("mine").alias("a"), F.explode(F.array("one", "two")).alias("b")).distinct()
    labels = table(spark, components(spark, links), "labels")
    firsts = nodes.select("doc_id", F.col("node").alias("id")).join(labels, "id").groupBy("component").agg(F.min("doc_id").alias("kept_in"))
    # a table, so that a component of very many stretches can be divided
    firsts = table(spark, firsts, "firsts")
    named_ = table(spark, labels.join(firsts, "component").select(F.col("id").alias("mine"), "kept_in"), "kept")
    out = table(spark, placed.join(named_, "mine").select("doc_id", "row", "first", "size", "kept_in"), "clustered")
    drop(spark, nodes, placed, labels, firsts, named_)
    return out


def repeated_spans(spark: SparkSession, docs: DataFrame, p: Paragraphs = Paragraphs()) -> DataFrame:
    """doc_id, row, spans array<struct<first, size, home>> of the word runs to remove, for each text that has any; ``home`` is the
    document in which the passage stays, ``row`` tells the texts of a repeated doc_id apart."""
    found = clusters(spark, repeated_runs(spark, named(docs), p))
    span = F.struct("first", "size", F.col("kept_in").alias("home"))
    return found.distinct().groupBy("doc_id", "row").agg(F.array_sort(F.collect_list(span)).alias("spans"))


def without(text: str, runs: list[dict]) -> tuple[str, int]:
    """A text without some runs of its words, each with the white space after it; and how many words these were."""
    raw = np.frombuffer(text.encode(), np.uint8)
    block = Block(raw, np.array([0, len(raw)]))
    keep, removed = np.ones(len(raw), bool), 0
    for r in runs:
        a, b = r["first"], min(r["first"] + r["size"], len(block.start))
        if a < b:
            stop = block.start[b] if b < len(block.start) else len(raw)
            keep[block.start[a] : stop] = False
            removed += b - a
    return raw[keep].tobytes().decode(), removed


def dedup_substrings(spark: SparkSession, docs: DataFrame, p: Paragraphs = Paragraphs()) -> DataFrame:
    """``docs`` with ``spans`` (word runs removed; null where none), ``n_removed`` words and ``clean_text``.

    A null or empty text stays as it is. A null doc_id takes no part. Rows that repeat a doc_id are one document: a passage that
    only they share stays; what earlier documents have is cut from each by its own spans. Documents are never dropped; all columns
    stay, whatever their names, and those of the result are replaced.
    """
    own = ["spans", "n_removed", "clean_text"]
    rows = docs.drop(*own)
    names = rows.columns
    id_, text = F.col("doc_id").cast("long"), F.col("text").cast("string")
    # a struct keeps the caller's names apart from those of the join
    held = rows.select(F.struct("*").alias("whole"), id_.alias("doc_id"), F.xxhash64(id_, text).alias("row"))
    spans = table(spark, repeated_spans(spark, rows, p), "spans")
    joined = held.join(spans, ["doc_id", "row"], "left").select("whole.*", "spans")

    def cut(batches):
        for whole in batches:
            for k in range(0, whole.num_rows, BATCH_ROWS):
                batch = whole.slice(k, BATCH_ROWS)
                lists = batch.column("spans")
                given = batch.column("text").cast(pa.string())
                texts, removed = [], np.zeros(batch.num_rows, np.int64)
                rows = np.flatnonzero(lists.is_valid().to_numpy(zero_copy_only=False) & given.is_valid().to_numpy(zero_copy_only=False))
                for i in rows:
                    text, removed[i] = without(given[i].as_py(), lists[i].as_py())
                    texts.append(text)
                mask = np.zeros(batch.num_rows, bool)
                mask[rows] = True
                clean = pc.replace_with_mask(given, pa.array(mask), pa.array(texts, pa.string()))
                yield pa.RecordBatch.from_arrays([*batch.columns[:-1], lists, pa.array(removed), clean], [*names, *own])

    kinds = [StructField("spans", joined.schema["spans"].dataType), StructField("n_removed", LongType()), StructField("clean_text", StringType())]
    return joined.mapInArrow(tidy(cut), StructType([*rows.schema.fields, *kinds]))
