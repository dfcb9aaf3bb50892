"""Nearest neighbours by vantage-point trees, one per shard of bounded size.

A node splits its vectors by the median distance to a vantage point. A search skips a side when the triangle inequality puts
all of it farther than the best found so far; the bound is divided by ``factor`` first, so that a value below one skips
more and may miss neighbours, and one is exact.

Shards are the leaves of a small vantage-point tree over all vectors, fitted on a bounded sample; a leaf that holds more than a
shard's rows is divided by a hash. A query first searches the leaf in which it lies itself; with the distances found there it then
goes to those leaves only that the same relaxed inequality does not rule out.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .store import drop, table
from .words import tidy

#: Vectors of a shard, queries that meet a shard's tree together, vectors of a tree's leaf.
SHARD_ROWS = 8192
QUERY_BLOCK = 4096
LEAF = 128
#: Bounds of what the driver holds: vectors of the sample, and leaves of the tree over all shards.
SAMPLE, MOST_LEAVES = 4096, 512
#: Vantage points that are tried for a split; the one of the most spread distances is taken.
TRIED = 6
#: Numbers that a distance matrix may hold at a time.
MATRIX = 1 << 20


def distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.sqrt(((a - b) ** 2).sum(-1))


def split(vectors: np.ndarray, rows: np.ndarray, random) -> tuple[np.ndarray, np.ndarray, float] | None:
    """A vantage point, the distances of ``rows`` to it and their median; none if no point parts them."""
    best = None
    for i in random.choice(rows, min(TRIED, len(rows)), replace=False):
        d = distances(vectors[rows], vectors[i])
        if best is None or d.std() > best[1].std():
            best = vectors[i], d, float(np.median(d))
    return best if (best[1] > best[2]).any() else None


class VPTree:
    """Over (id, vector) rows. Of equal vectors the ``most`` least ids are kept: more can never be wanted at once."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, most: int, seed: int = 7):
        order = np.lexsort((ids, *vectors.T[::-1])) if len(ids) else np.zeros(0, np.int64)
        ids, vectors = ids[order], vectors[order]
        new = np.ones(len(ids), bool)
        new[1:] = (vectors[1:] != vectors[:-1]).any(1)
        start = np.maximum.accumulate(np.where(new, np.arange(len(ids)), 0))
        keep = np.arange(len(ids)) - start < most
        self.ids, self.vectors = ids[keep], np.ascontiguousarray(vectors[keep])
        self.nodes: list[tuple] = []
        self.root = self._build(np.arange(len(self.ids)), np.random.default_rng(seed)) if len(self.ids) else -1

    def _build(self, rows: np.ndarray, random) -> int:
        at = len(self.nodes)
        self.nodes.append((rows,))
        found = split(self.vectors, rows, random) if len(rows) > LEAF else None
        if found:
            vantage, d, middle = found
            near = d <= middle
            spans = (float(d[near].min()), middle, float(d[~near].min()), float(d[~near].max()))
            self.nodes[at] = (vantage, spans, self._build(rows[near], random), self._build(rows[~near], random))
        return at

    def search(self, ids: np.ndarray, queries: np.ndarray, k: int, factor: float, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(distances, ids, vectors compared) of each query's k nearest within its ``bound`` but its own id, ties to the smaller
        id; unfilled places are infinitely far. All queries walk the tree together, each to its nearer side first."""
        n = len(ids)
        best, who = np.full((n, k), np.inf), np.full((n, k), np.iinfo(np.int64).max)
        seen = np.zeros(n, np.int64)
        stack = [(self.root, np.arange(n), np.zeros(n))] if self.root >= 0 else []
        while stack:
            node, active, least = stack.pop()
            open_ = least <= np.minimum(best[active, -1], bound[active])
            active, least = active[open_], least[open_]
            if not len(active):
                continue
            node = self.nodes[node]
            if len(node) == 1:
                rows = node[0]
                seen[active] += len(rows)
                step = max(1, MATRIX // max(1, len(rows) * self.vectors.shape[1]))
                for c in range(0, len(active), step):
                    self._offer(active[c : c + step], rows, ids, queries, bound, best, who)
                continue
            vantage, (lo_in, hi_in, lo_out, hi_out), inner, outer = node
            d = distances(queries[active], vantage)
            inside = np.maximum(least, np.maximum(np.maximum(d - hi_in, lo_in - d), 0.0) / factor)
            outside = np.maximum(least, np.maximum(np.maximum(lo_out - d, d - hi_out), 0.0) / factor)
            first = inside <= outside
            stack += [(inner, active[~first], inside[~first]), (outer, active, outside), (inner, active[first], inside[first])]
        return best, who, seen

    def _offer(self, active, rows, ids, queries, bound, best, who) -> None:
        d = distances(queries[active][:, None], self.vectors[rows][None])
        found = np.broadcast_to(self.ids[rows], d.shape)
        d[(found == ids[active][:, None]) | (d > bound[active][:, None])] = np.inf
        better = (d <= best[active, -1:]).any(1)
        active = active[better]
        d = np.concatenate([best[active], d[better]], 1)
        found = np.concatenate([who[active], found[better]], 1)
        k = best.shape[1]
        by_id = np.argsort(found, 1, kind="stable")
        d, found = np.take_along_axis(d, by_id, 1), np.take_along_axis(found, by_id, 1)
        order = np.argsort(d, 1, kind="stable")[:, :k]
        best[active], who[active] = np.take_along_axis(d, order, 1), np.take_along_axis(found, order, 1)


class Shards:
    """The tree over all shards: leaves are numbered, and every leaf is bounded by the splits above it."""

    def __init__(self, sample: np.ndarray, leaves: int):
        self.vantage: list[np.ndarray] = []
        self.nodes: list[tuple] = []
        self.leaves = 0
        self._build(sample, np.arange(len(sample)), leaves, np.random.default_rng(3))

    def _build(self, sample: np.ndarray, rows: np.ndarray, leaves: int, random) -> int:
        at = len(self.nodes)
        self.nodes.append(())
        found = split(sample, rows, random) if leaves > 1 and len(rows) > 2 * TRIED else None
        if not found:
            self.nodes[at] = (self.leaves,)
            self.leaves += 1
            return at
        vantage, d, middle = found
        near = d <= middle
        inner = self._build(sample, rows[near], leaves // 2, random)
        self.nodes[at] = (vantage, middle, inner, self._build(sample, rows[~near], leaves - leaves // 2, random))
        return at

    def bounds(self, vectors: np.ndarray) -> np.ndarray:
        """Least distance that any vector of each leaf can have, by the splits; of a vector's own leaf, and of no other, -1."""
        out = np.zeros((len(vectors), self.leaves))
        stack = [(0, np.full(len(vectors), -1.0))] if len(vectors) else []
        while stack:
            at, least = stack.pop()
            if len(self.nodes[at]) == 1:
                out[:, self.nodes[at][0]] = least
                continue
            vantage, middle, inner, outer = self.nodes[at]
            d = distances(vectors, vantage)
            stack.append((inner, np.where(d <= middle, least, np.maximum(least, d - middle))))
            stack.append((outer, np.where(d > middle, least, np.maximum(least, middle - d))))
        return out


def _finite(vector):
    return F.expr(f"{vector} is not null and size({vector}) > 0 and forall({vector}, x -> x is not null and not isnan(x) and abs(x) < double('infinity')) and exists({vector}, x -> x <> 0)")


def matrix(column) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return flat.flatten().to_numpy(zero_copy_only=False).reshape(len(flat), -1) if len(flat) else np.zeros((0, 1))


FOUND = "query_id long, vec_id long, score double, compared long"


def nearest(spark: SparkSession, vectors: DataFrame, queries: DataFrame, k: int = 10, factor: float = 0.18) -> DataFrame:
    """query_id, rank, vec_id, score, compared: each query's ``k`` nearest rows of ``vectors`` found, its own id left out, and how
    many vectors it was compared with.

    Both tables have vec_id and embedding. Vectors that are null, zero, or hold null or non-finite components take no part;
    all others must be of one length. Rows with a null id take no part. Rows that repeat an id are all candidates; of those that
    repeat id and vector, more than k + 1 cannot matter. Other columns are ignored. An empty table gives an empty result.
    """
    take = lambda df: df.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v")).where(_finite("v") & F.col("vec_id").isNotNull())
    rows, asked = take(vectors), take(queries)
    n = rows.count()
    # at most SAMPLE rows
    sample = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).select("v").collect()
    shards = Shards(np.array([r.v for r in sample], float), min(MOST_LEAVES, -(-n // SHARD_ROWS)))
    # bounded by MOST_LEAVES vectors
    top = spark.sparkContext.broadcast(shards)

    def deal(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, v = batch.column("vec_id").to_numpy(), matrix(batch.column("v"))
            # copies of a row beyond k + 1 go where they are first met
            same = np.unique(np.column_stack([ids, v.view(np.int64)]), axis=0, return_inverse=True)[1].ravel()
            order = np.argsort(same, kind="stable")
            first = np.searchsorted(same[order], same[order])
            keep = np.sort(order[np.arange(len(order)) - first <= k])
            leaf = np.argmin(top.value.bounds(v[keep]), 1).astype(np.int32)
            part = batch.take(pa.array(keep))
            yield pa.RecordBatch.from_arrays([part.column("vec_id"), part.column("v"), pa.array(leaf)], ["vec_id", "v", "leaf"])

    dealt = table(spark, rows.mapInArrow(tidy(deal), "vec_id long, v array<double>, leaf int"), "dealt")
    # one row a leaf
    held = {r.leaf: r["count"] for r in dealt.groupBy("leaf").count().collect()}
    parts = [max(1, -(-held.get(leaf, 0) // (2 * SHARD_ROWS))) for leaf in range(shards.leaves)]
    part_of = F.element_at(F.array(*map(F.lit, parts)), F.col("leaf") + 1)

    def build(t: pa.Table) -> pa.Table:
        tree = VPTree(t.column("vec_id").to_numpy(), matrix(t.column("v")), k + 1)
        return pa.table({"leaf": t.column("leaf")[:1], "part": t.column("part")[:1], "tree": pa.array([pickle.dumps(tree, 5)], pa.binary())})

    numbered = dealt.withColumn("part", F.pmod(F.xxhash64("vec_id", F.lit(17)), part_of).cast("int"))
    trees = table(spark, numbered.groupBy("leaf", "part").applyInArrow(build, "leaf int, part int, tree binary"), "trees")
    blocks = max(1, -(-asked.count() // QUERY_BLOCK))

    def gather(t: pa.Table) -> pa.Table:
        block = pickle.dumps((t.column("vec_id").to_numpy(), matrix(t.column("v")), t.column("bound").to_numpy()), 5)
        return pa.table({"leaf": t.column("leaf")[:1], "asked": pa.array([block], pa.binary())})

    def search(batches):
        for batch in batches:
            for tree, block in zip(batch.column("tree"), batch.column("asked")):
                tree, (ids, asked_, bound) = pickle.loads(tree.as_buffer()), pickle.loads(block.as_buffer())
                score, who, seen = tree.search(ids, asked_, k, factor, bound)
                hit = np.isfinite(score)
                at = np.nonzero(hit)[0]
                # a row without a neighbour carries the number of comparisons
                none, zero = np.full(len(ids), np.nan), np.zeros(len(ids), np.int64)
                score, who = np.concatenate([score[hit], none]), np.concatenate([who[hit], zero])
                empty = np.isnan(score)
                made = [pa.array(np.concatenate([ids[at], ids])), pa.array(who, mask=empty), pa.array(score, mask=empty)]
                made.append(pa.array(np.concatenate([np.zeros(len(at), np.int64), seen])))
                yield pa.RecordBatch.from_arrays(made, ["query_id", "vec_id", "score", "compared"])

    def found_in(visits: DataFrame, name: str) -> DataFrame:
        """Search ``visits(vec_id, v, bound, leaf)``; queries that visit a leaf go to its trees in blocks."""
        block = F.pmod(F.xxhash64("vec_id", F.lit(5)), F.lit(blocks)).cast("int")
        packed = visits.groupBy("leaf", block.alias("block")).applyInArrow(gather, "leaf int, asked binary")
        return table(spark, packed.join(trees, "leaf").select("tree", "asked").mapInArrow(tidy(search), FOUND), name)

    def visits_of(df: DataFrame, others: bool) -> DataFrame:
        """The leaves a query goes to: its own, or all others that its bound leaves open."""

        def run(batches):
            for batch in batches:
                if not batch.num_rows:
                    continue
                bound, least = batch.column("bound").to_numpy(), top.value.bounds(matrix(batch.column("v")))
                own = np.argmin(least, 1)
                wanted = np.zeros(least.shape, bool)
                wanted[np.arange(len(own)), own] = True
                if others:
                    wanted = ~wanted & (np.maximum(least, 0.0) / factor <= bound[:, None])
                at, leaf = np.nonzero(wanted)
                part = batch.take(pa.array(at))
                yield pa.RecordBatch.from_arrays([*part.select(["vec_id", "v", "bound"]).columns, pa.array(leaf.astype(np.int32))], ["vec_id", "v", "bound", "leaf"])

        return df.mapInArrow(run, "vec_id long, v array<double>, bound double, leaf int")

    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    ranked = lambda df: df.where("vec_id is not null").withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    # a query's rows that repeat an id are searched one by one, but give one answer
    once = asked.groupBy("vec_id").agg(F.min("v").alias("v"))
    near = found_in(visits_of(once.withColumn("bound", F.lit(float("inf"))), False), "near")
    kth = ranked(near).where(F.col("rank") == k).select(F.col("query_id").alias("vec_id"), F.col("score").alias("bound"))
    bounded = once.join(kth, "vec_id", "left").withColumn("bound", F.coalesce("bound", F.lit(float("inf"))))
    far = found_in(visits_of(bounded, True), "far")
    drop(spark, dealt, trees)
    both = near.unionByName(far)
    work = both.groupBy("query_id").agg(F.sum("compared").alias("compared"))
    return ranked(both.drop("compared")).join(work, "query_id").select("query_id", "rank", "vec_id", "score", "compared")
