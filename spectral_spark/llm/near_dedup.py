"""MinHash near-deduplication with sequential Bayesian verification.

Signatures are banded; documents that share a band are candidates. A candidate pair's signatures are compared one batch of
positions at a time: after n positions with m matches the similarity has a Beta(m + 1, n - m + 1) posterior, and the pair is
dropped as soon as the probability that it reaches the threshold falls below ``miss``. Survivors are confirmed on full sets.

Scale: texts become a fixed-size signature in one pass; documents with equal sets are one node, so exact copies of any number
cost one row. A band is first compared with one hub (the member that shares most bands), which is linear in its size, and
what is then linked is merged. Only pairs of a band that are still apart are compared with each other, in blocks of bounded
size that many tasks share; nothing is capped. With the defaults a pair at the threshold is missed by all bands
with probability 4e-7.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import components
from .store import drop, table
from .words import Block, distinct, fold, mix, shingles, text_blocks, tidy


@dataclass(frozen=True)
class MinHash:
    """Shingle size, similarity threshold (percent), bands x rows, batch of the sequential test and its miss probability; documents of
    a block, and shingles if they are long."""

    words: int = 3
    percent: int = 85
    bands: int = 25
    rows: int = 5
    batch: int = 32
    batches: int = 4
    miss: float = 1e-5
    block: int = 256
    block_shingles: int = 1 << 21

    @property
    def size(self) -> int:
        return self.batch * self.batches


@lru_cache
def least_matches(percent: int, batch: int, batches: int, miss: float) -> tuple[int, ...]:
    """For n = batch, 2 batch, ...: the fewest matches m at which P(similarity >= threshold | m of n) >= miss.

    With a uniform prior that tail is the binomial P(X <= m), X of n + 1 trials at the threshold.
    """
    t, out = percent / 100, []
    for n in range(batch, batch * batches + 1, batch):
        tail = 0.0
        for m in range(n + 1):
            tail += comb(n + 1, m) * t**m * (1 - t) ** (n + 1 - m)
            if tail >= miss:
                break
        out.append(m)
    return tuple(out)


def _coefficients(size: int) -> tuple[np.ndarray, np.ndarray]:
    k = np.arange(size, dtype=np.uint64)
    return mix(k, 11) | np.uint64(1), mix(k, 12)


def signature(sets: np.ndarray, limits: np.ndarray, size: int) -> np.ndarray:
    """Minima of ``size`` hash functions over each (non-empty) set, as uint32 rows."""
    a, b = _coefficients(size)
    out = np.full((size, len(limits) - 1), 0xFFFFFFFF, np.uint64)
    for k in range(size):
        fold(sets, limits, lambda x, k=k: (x * a[k] + b[k]) >> np.uint64(32), np.minimum, out[k])
    return np.ascontiguousarray(out.T.astype(np.uint32))


def set_digests(sets: np.ndarray, limits: np.ndarray) -> list[np.ndarray]:
    """Two 64-bit sums of mixed members, whatever their order."""
    return [fold(sets, limits, lambda x, seed=seed: mix(x, seed), np.add, np.zeros(len(limits) - 1, np.uint64)).view(np.int64) for seed in (21, 22)]


def band_keys(signatures: np.ndarray, bands: int, rows: int) -> np.ndarray:
    out = np.empty((len(signatures), bands), np.uint64)
    for k in range(bands):
        h = np.full(len(signatures), k + 1, np.uint64)
        for r in range(rows):
            h = mix(h * np.uint64(0xD6E8FEB86659FD93) + signatures[:, k * rows + r], 3)
        out[:, k] = h
    return out.view(np.int64)


SIGNED = "doc_id long, n_shingles long, d1 long, d2 long, sig binary"


def sign(docs: DataFrame, p: MinHash) -> DataFrame:
    """doc_id, set size, 128-bit digest of the set, signature (null for an empty set), in one pass without a shuffle."""

    def run(batches):
        for batch in batches:
            ids = batch.column("doc_id")
            for i, j, data, at in text_blocks(batch.column("text")):
                block = Block(data, at)
                sets, limits = distinct(*shingles(block.hashes(), block.first, p.words))
                n = np.diff(limits)
                full = np.flatnonzero(n)
                d = set_digests(sets, limits)
                sig = np.full(len(n), None, object)
                if len(full):
                    tight = np.concatenate([[0], np.cumsum(n[full])])
                    sig[full] = [x.tobytes() for x in signature(sets, tight, p.size)]
                columns = [ids.slice(i, j - i), pa.array(n), pa.array(d[0]), pa.array(d[1]), pa.array(list(sig), pa.binary())]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_shingles", "d1", "d2", "sig"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), SIGNED)


def _bands(nodes: DataFrame, p: MinHash) -> DataFrame:
    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            sig = np.frombuffer(b"".join(batch.column("sig").to_pylist()), np.uint32).reshape(-1, p.size)
            ids, sizes = (np.repeat(batch.column(c).to_numpy(zero_copy_only=False), p.bands) for c in ("id", "size"))
            yield pa.RecordBatch.from_arrays([pa.array(band_keys(sig, p.bands, p.rows).ravel()), pa.array(ids), pa.array(sizes)], ["bucket", "id", "size"])

    return nodes.select("id", "sig", "size").mapInArrow(tidy(run), "bucket long, id long, size int")


def _sequential(left: np.ndarray, right: np.ndarray, p: MinHash) -> np.ndarray:
    """Indices of the pairs (rows of two signature matrices) that no batch has pruned."""
    alive, matches = np.arange(len(left)), np.zeros(len(left), np.int64)
    for k, least in enumerate(least_matches(p.percent, p.batch, p.batches, p.miss)):
        cut = slice(k * p.batch, (k + 1) * p.batch)
        matches = matches + (left[alive, cut] == right[alive, cut]).sum(1)
        keep = matches >= least
        alive, matches = alive[keep], matches[keep]
    return alive


def survivors(pairs: DataFrame, nodes: DataFrame, p: MinHash) -> DataFrame:
    """The pairs (a, b) that the sequential test leaves."""
    one = nodes.select(F.col("id").alias("a"), F.col("sig").alias("sa"))
    two = nodes.select(F.col("id").alias("b"), F.col("sig").alias("sb"))

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            left, right = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint32).reshape(-1, p.size) for c in ("sa", "sb"))
            yield batch.select(["a", "b"]).take(pa.array(_sequential(left, right, p)))

    return pairs.join(one, "a").join(two, "b").select("a", "b", "sa", "sb").mapInArrow(tidy(run), "a long, b long")


def texts_of(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """(id, text) of the ends of pairs."""
    return texts.join(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "id", "left_semi")


def digested(texts: DataFrame, p: MinHash) -> DataFrame:
    """``texts(id, text)`` with the digest of each text's set."""

    def run(batches):
        for batch in batches:
            for i, j, data, at in text_blocks(batch.column("text")):
                block = Block(data, at)
                d = set_digests(*distinct(*shingles(block.hashes(), block.first, p.words)))
                part = batch.slice(i, j - i)
                yield pa.RecordBatch.from_arrays([*part.select(["id", "text"]).columns, *map(pa.array, d)], ["id", "text", "d1", "d2"])

    return texts.mapInArrow(tidy(run), "id long, text string, d1 long, d2 long")


def confirm(pairs: DataFrame, texts: DataFrame, p: MinHash) -> DataFrame:
    """The pairs whose full shingle sets reach the threshold; ``texts(id, text)``, whole texts, should be a stored table: then the
    joins have an exchange on both sides, and the pairs of a hub can be divided."""
    one = texts.select(F.col("id").alias("a"), F.col("text").alias("ta"))
    two = texts.select(F.col("id").alias("b"), F.col("text").alias("tb"))

    def run(batches):
        for batch in batches:
            keep = []
            for k, (x, y) in enumerate(zip(_sets_of(batch.column("ta"), p), _sets_of(batch.column("tb"), p))):
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * both >= p.percent * (len(x) + len(y) - both))
            if any(keep):
                yield batch.select(["a", "b"]).filter(pa.array(keep))

    return pairs.join(one, "a").join(two, "b").select("a", "b", "ta", "tb").mapInArrow(tidy(run), "a long, b long")


def _apart(members: DataFrame, comp: DataFrame) -> DataFrame:
    """bucket, id, comp of the buckets that hold more than one component, with their members and the sum of these' set sizes."""
    seen = members.join(comp, "id", "left").withColumn("comp", F.coalesce("component", "id")).drop("component")
    split = seen.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("n"), F.sum("size").alias("all"))
    split = split.where("lo <> hi").select("bucket", "n", "all")
    return seen.join(split, "bucket")


def _similar(sig: np.ndarray, ids: np.ndarray, comps: np.ndarray, mine: np.ndarray, x: int, y: int, bucket: int, p: MinHash):
    """(i, partners) of rows of blocks ``x`` and ``y`` in different components that the sequential test leaves.

    A pair that shares several bands is looked at in the first of them only.
    """
    keys = band_keys(sig, p.bands, p.rows)
    band = int(np.argmax((keys == bucket).all(0)))
    left, right = np.flatnonzero(mine == x), np.flatnonzero(mine == y)
    least = least_matches(p.percent, p.batch, p.batches, p.miss)[0]
    for i in left:
        other = right[(comps[right] != comps[i]) & ((ids[right] > ids[i]) | (x != y))]
        other = other[(sig[other, : p.batch] == sig[i, : p.batch]).sum(1) >= least]
        if band:
            other = other[~(keys[other, :band] == keys[i, :band]).any(1)]
        if len(other):
            other = other[_sequential(np.broadcast_to(sig[i], (len(other), p.size)), sig[other], p)]
        if len(other):
            yield i, other


def _block(t: pa.Table, p: MinHash) -> tuple:
    sig = np.frombuffer(b"".join(t.column("sig").to_pylist()), np.uint32).reshape(-1, p.size)
    ids, comps, mine = (t.column(c).to_numpy() for c in ("id", "comp", "mine"))
    return sig, ids, comps, mine, *(t.column(c)[0].as_py() for c in ("x", "y", "bucket"))


def _sets_of(column, p: MinHash):
    for _, _, data, at in text_blocks(column):
        block = Block(data, at)
        sets, limits = distinct(*shingles(block.hashes(), block.first, p.words))
        yield from (sets[x:y] for x, y in zip(limits[:-1], limits[1:]))


def links_across(apart: DataFrame, nodes: DataFrame, texts: DataFrame, p: MinHash) -> DataFrame:
    """Links that join different components of a bucket; among its pairs, enough to connect all that are linked.

    Blocks are first compared by signature alone. Texts then go only to blocks in which they have a partner left,
    and are confirmed there: a pair that other links of the block connect already need not be.
    """
    blocks = F.greatest(F.ceil(F.col("n") / p.block), F.ceil(F.col("all") / p.block_shingles)).cast("int")
    dealt = apart.withColumn("k", blocks).withColumn("mine", F.pmod(F.xxhash64("id"), F.col("k")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    dealt = dealt.select("bucket", F.least("mine", "other").alias("x"), F.greatest("mine", "other").alias("y"), "mine", "id", "comp")
    signs = nodes.select("id", "sig")

    def partnered(t: pa.Table) -> pa.Table:
        block = _block(t, p)
        rows = np.unique(np.concatenate([np.zeros(0, np.int64), *(np.append(o, i) for i, o in _similar(*block, p))]))
        return t.drop_columns(["sig"]).take(pa.array(rows.astype(np.int64)))

    def confirm_block(t: pa.Table) -> pa.Table:
        sig, ids, comps, mine, x, y, bucket = _block(t, p)
        sets = list(_sets_of(t.column("text"), p))
        parent: dict[int, int] = {int(c): int(c) for c in comps}

        def root(c: int) -> int:
            while parent[c] != c:
                parent[c] = c = parent[parent[c]]
            return c

        found = []
        for i, other in _similar(sig, ids, comps, mine, x, y, bucket, p):
            mine_ = root(int(comps[i]))
            other = [j for j in other if root(int(comps[j])) != mine_]
            if not other or not len(sets[i]):
                continue
            sizes = np.array([len(sets[j]) for j in other])
            stacked = np.concatenate([sets[j] for j in other])
            at = np.minimum(np.searchsorted(sets[i], stacked), len(sets[i]) - 1)
            total = np.concatenate([[0], np.cumsum(sets[i][at] == stacked)])
            ends = np.cumsum(sizes)
            both = total[ends] - total[ends - sizes]
            for j in np.flatnonzero(100 * both >= p.percent * (sizes + len(sets[i]) - both)):
                a, b = root(int(comps[i])), root(int(comps[other[j]]))
                if a != b:
                    parent[b] = a
                    found.append((int(ids[i]), int(ids[other[j]])))
        return pa.table({"a": pa.array([f[0] for f in found], pa.int64()), "b": pa.array([f[1] for f in found], pa.int64())})

    # blocks are few bytes and much work: their number of tasks must not follow their bytes
    keys, tasks = ["bucket", "x", "y"], int(apart.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    kept = dealt.join(signs, "id").repartition(tasks, *keys).groupBy(*keys).applyInArrow(partnered, "id long, bucket long, x int, y int, mine int, comp long")
    full = kept.join(signs, "id").join(texts, "id")
    return full.repartition(tasks, *keys).groupBy(*keys).applyInArrow(confirm_block, "a long, b long")


def near_duplicates(spark: SparkSession, docs: DataFrame, p: MinHash = MinHash()) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept.

    Null and empty texts have an empty set and are linked with nothing. A null doc_id is linked with nothing, has a null
    component and is kept. Rows that repeat a doc_id are one document, as far as links go, whether or not their texts are the
    same: a copy of any of them is a copy of the document. Other columns are ignored.
    """
    signed = table(spark, sign(docs, p), "signed")
    some = signed.where("sig is not null and doc_id is not null")
    # a node is a set, named by its least document
    nodes = some.groupBy("d1", "d2").agg(F.min("doc_id").alias("id"), F.min_by("sig", "doc_id").alias("sig"), F.max("n_shingles").cast("int").alias("size"))
    repeated = table(spark, some.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id"), "repeated")
    some_repeat = not repeated.isEmpty()
    if some_repeat:
        # one document can be the least of many sets: those of repeated ids are named by their digests
        many = repeated.select(F.col("doc_id").alias("id"), F.lit(True).alias("many"))
        nodes = nodes.join(many, "id", "left").withColumn("id", F.when(F.col("many"), F.xxhash64("d1", "d2")).otherwise(F.col("id"))).drop("many")
    nodes = table(spark, nodes, "nodes")
    keys = _bands(nodes, p)
    shared = keys.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1")
    members = table(spark, keys.join(shared, "bucket"), "members")
    degree = members.groupBy("id").agg(F.sum("n").alias("degree"))
    hub = members.join(degree, "id").groupBy("bucket").agg((-F.max(F.struct("degree", (-F.col("id")).alias("i")))["i"]).alias("hub"))
    pairs = members.join(hub, "bucket").where("id <> hub")
    pairs = pairs.select(F.least("id", "hub").alias("a"), F.greatest("id", "hub").alias("b")).distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string").alias("text")).where("id is not null")
    if some_repeat:
        ids = repeated.select(F.col("doc_id").alias("id"))
        named = digested(texts.join(ids, "id", "left_semi").distinct(), p).drop("id").join(nodes.select("d1", "d2", "id"), ["d1", "d2"])
        texts = texts.join(ids, "id", "left_anti").unionByName(named.groupBy("id").agg(F.first("text").alias("text")))
    texts = texts.join(nodes.select("id"), "id", "left_semi")
    near = table(spark, survivors(pairs, nodes, p), "near")
    ends = table(spark, texts_of(near, texts), "texts")
    links = table(spark, confirm(near, ends, p), "confirmed")
    drop(spark, ends)
    # a table, so that joins with it have an exchange on both sides and a large class of copies can be divided
    same = table(spark, nodes.select("d1", "d2", "id"), "classes")
    if some_repeat:
        # the nodes of a document's texts are one
        own = some.join(repeated, "doc_id", "left_semi").join(same, ["d1", "d2"]).select("doc_id", "id").distinct()
        own = table(spark, own, "own")
        least = table(spark, own.groupBy("doc_id").agg(F.min("id").alias("a")), "least")
        joined = own.join(least, "doc_id").where("a <> id").select("a", F.col("id").alias("b"))
        links = table(spark, links.unionByName(joined), "confirmed")
    first = table(spark, components(spark, links), "first")
    more = table(spark, links_across(_apart(members.select("bucket", "id", "size"), first), nodes, texts, p), "across")
    final = table(spark, components(spark, links.unionByName(more)), "components")
    out = signed.join(same, ["d1", "d2"], "left").join(final, "id", "left").withColumn("component", F.coalesce("component", "id"))
    if some_repeat:
        out = table(spark, out.select("doc_id", "n_shingles", "sig", "component"), "labelled")
        least = table(spark, out.where("doc_id is not null").groupBy("component").agg(F.min("doc_id").alias("least")), "least")
        out = out.join(least, "component", "left").withColumn("component", F.col("least"))
    drop(spark, members, near, first, nodes)
    component = F.when(F.col("doc_id").isNull(), F.lit(None).cast("long")).when(F.col("sig").isNull(), F.col("doc_id")).otherwise(F.col("component"))
    out = out.select("doc_id", "n_shingles", component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def drop_copies(spark: SparkSession, docs: DataFrame, p: MinHash = MinHash()) -> DataFrame:
    """``docs`` with one row of each group of near copies: that of the least doc_id. All columns stay, whatever their names.

    Rows are judged one by one: of rows that share a doc_id, or have none, a copy goes and another text stays; of rows that repeat
    both id and text one stays. Rows without words are no copies of each other.
    """
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id")).groupBy("doc_id").agg(F.count("*").alias("n"))
    shared = table(spark, ids.where("n > 1 or doc_id is null").select("doc_id"), "shared_ids")
    if shared.isEmpty():
        gone = near_duplicates(spark, docs, p).where("not kept").select("doc_id")
        return docs.join(gone, docs["doc_id"].cast("long") == gone["doc_id"], "left_anti")
    whole = docs.select(F.struct("*").alias("whole"), F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string").alias("text"))
    many = F.col("id").isNull() | F.col("many")
    mark = shared.where("doc_id is not null").select(F.col("doc_id").alias("id"), F.lit(True).alias("many"))
    # beyond all usual ids, so that a row with an id of its own stays rather than one of these
    name = F.shiftright(F.xxhash64("id", "text"), 2).bitwiseAND(F.lit((1 << 61) - 1)) + F.lit(1 << 62)
    rows = whole.join(mark, "id", "left").withColumn("many", F.coalesce(many, F.lit(False))).withColumn("name", F.when(F.col("many"), name).otherwise(F.col("id")))
    once = rows.where("many").dropDuplicates(["name"])
    rows = table(spark, rows.where("not many").unionByName(once).select("name", "text", "whole"), "rows")
    gone = near_duplicates(spark, rows.select(F.col("name").alias("doc_id"), "text"), p).where("not kept").select(F.col("doc_id").alias("name"))
    return rows.join(gone, "name", "left_anti").select("whole.*")
