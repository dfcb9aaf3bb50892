"""Toxicity by a classifier chain of linear models.

Categories are predicted one after another; each later model also sees the probabilities of the earlier categories. Those that
it is trained on are out-of-fold, so that it learns how far an earlier prediction can be trusted. Features are the distinct words
of a text, hashed; each model takes those most dependent on its category. Training uses a bounded, hash-ordered sample of
labelled documents; scoring is one pass over all documents.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, StructField, StructType

from .words import LOWER, Block, mix, text_blocks, tidy

#: Every ASCII byte but letters and digits ends a word here, so that punctuation does not hide it.
NOT_WORD = np.ones(256, bool)
NOT_WORD[128:] = False
for _lo, _hi in ("09", "AZ", "az"):
    NOT_WORD[ord(_lo) : ord(_hi) + 1] = False


#: Bytes of the prefixes that are features beside whole words; inflected and compound forms share them.
PREFIXES = (4, 6)
#: Being seen at least so often in a text is a feature, too.
OFTEN = (2, 3, 5)


@dataclass(frozen=True)
class ChainSettings:
    """``sample`` bounds the labelled documents that training reads, ``sample_features`` the features of each (the first by a
    hash, of the whole text); all else is the usual regularised logistic regression."""

    sample: int = 6000
    sample_features: int = 8192
    buckets: int = 1 << 20
    chosen: int = 1000
    folds: int = 4
    ridge: float = 0.1
    steps: int = 400
    threshold: float = 0.4


#: Words whose features are counted together.
PART_WORDS = 1 << 16


def _added(keys: list[np.ndarray], times: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys and the sum of their counts."""
    once, where = np.unique(np.concatenate(keys), return_inverse=True)
    return once, np.bincount(where, np.concatenate(times), len(once)).astype(np.int64)


def features(block: Block, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct feature numbers of every text (its words, prefixes of longer ones, and how often each stands there) and their limits."""
    size = block.end - block.start
    streams = [(block.hashes(LOWER), None)]
    streams += [(block.hashes(LOWER, n) + np.uint64(n), np.flatnonzero(size > n)) for n in PREFIXES]
    keys, times = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
    for hashes, at in streams:
        for c in range(0, len(hashes), PART_WORDS):
            words = np.arange(c, min(c + PART_WORDS, len(hashes))) if at is None else at[c : c + PART_WORDS]
            owner = (np.searchsorted(block.first, words, "right") - 1).astype(np.uint64)
            number = (hashes[c : c + PART_WORDS] >> np.uint64(20)) % np.uint64(buckets)
            once, count = np.unique(owner * np.uint64(buckets) + number, return_counts=True)
            keys.append(once)
            times.append(count)
            if len(keys) > 16:
                keys, times = ([x] for x in _added(keys, times))
    once, count = _added(keys, times)
    found = [once]
    for n in OFTEN:
        more = once[count >= n]
        found.append(more - more % np.uint64(buckets) + mix(more % np.uint64(buckets), n) % np.uint64(buckets))
    both = np.unique(np.concatenate(found))
    limits = np.searchsorted(both, np.arange(len(block.counts) + 1, dtype=np.uint64) * np.uint64(buckets))
    return (both % np.uint64(buckets)).astype(np.int64), limits


def _row_sums(values: np.ndarray, limits: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0.0], np.cumsum(values)])
    return total[limits[1:]] - total[limits[:-1]]


def choose_features(index: np.ndarray, limits: np.ndarray, y: np.ndarray, s: ChainSettings) -> np.ndarray:
    """The ``chosen`` features most dependent on the label (chi-square); a map from feature to position, -1 for the rest."""
    rows = np.repeat(np.arange(len(y)), np.diff(limits))
    seen = np.bincount(index, minlength=s.buckets).astype(float)
    hit = np.bincount(index, weights=y[rows], minlength=s.buckets)
    n, positive = len(y), y.sum()
    expected = seen * positive / max(n, 1)
    chi = (hit - expected) ** 2 / np.maximum(expected, 1e-9) + (hit - expected) ** 2 / np.maximum(seen - expected, 1e-9)
    chi[seen < 2] = 0
    best = np.argsort(-chi, kind="stable")[: s.chosen]
    best = np.sort(best[chi[best] > 0])
    known = np.full(s.buckets, -1, np.int32)
    known[best] = np.arange(len(best))
    return known


def fit_logistic(index: np.ndarray, limits: np.ndarray, extra: np.ndarray, y: np.ndarray, size: int, s: ChainSettings) -> np.ndarray:
    """Weights (features, extra columns, intercept) by accelerated gradient descent on the ridge-penalised loss."""
    rows = np.repeat(np.arange(len(y)), np.diff(limits))
    n, k = max(len(y), 1), extra.shape[1]
    w = np.zeros(size + k + 1)
    rate = y.mean() if len(y) else 0.5
    w[-1] = np.log((rate + 1e-3) / (1 - rate + 1e-3))
    first, second = np.zeros_like(w), np.zeros_like(w)
    for t in range(1, s.steps + 1):
        z = _row_sums(w[index], limits) + extra @ w[size : size + k] + w[-1]
        g = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - y
        grad = np.concatenate([np.bincount(index, g[rows], size), extra.T @ g, [g.sum()]])
        grad[:-1] += s.ridge * w[:-1]
        grad /= n
        first, second = 0.9 * first + 0.1 * grad, 0.999 * second + 0.001 * grad**2
        w -= 0.05 * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)
    return w


def logits(w: np.ndarray, index: np.ndarray, limits: np.ndarray, extra: np.ndarray) -> np.ndarray:
    size, k = len(w) - extra.shape[1] - 1, extra.shape[1]
    return _row_sums(w[index], limits) + extra @ w[size : size + k] + w[-1]


def probability(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _inner(known: np.ndarray, index: np.ndarray, limits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of the known features of every text, and their limits."""
    to = known[index]
    keep = to >= 0
    return to[keep], np.concatenate([[0], np.cumsum(keep)])[limits]


@dataclass
class Chain:
    """A model for each category: its features and its weights."""

    categories: tuple[str, ...]
    models: list[tuple[np.ndarray, np.ndarray]]
    settings: ChainSettings

    def predict(self, index: np.ndarray, limits: np.ndarray) -> np.ndarray:
        """Probabilities, a column for each category."""
        seen = np.zeros((len(limits) - 1, 0))
        for known, w in self.models:
            seen = np.column_stack([seen, probability(logits(w, *_inner(known, index, limits), seen))])
        return seen


def train_chain(index: np.ndarray, limits: np.ndarray, labels: np.ndarray, categories: tuple[str, ...], s: ChainSettings) -> Chain:
    """``labels``: 0/1 rows, NaN where a category's label is not known.

    A category is learned from the rows that have its label. What later models see of it is predicted, for every row, by models
    that were not fitted on the row.
    """
    chain = Chain(categories, [], s)
    n = len(labels)
    fold = np.arange(n) % s.folds
    seen = np.zeros((n, 0))

    def fit(rows, seen, y):
        part = _rows_of(index, limits, rows)
        known = choose_features(*part, y[rows], s)
        return known, fit_logistic(*_inner(known, *part), seen[rows], y[rows], int((known >= 0).sum()), s)

    for c in range(len(categories)):
        y = labels[:, c].astype(float)
        given = ~np.isnan(y)
        chain.models.append(fit(given, seen, y))
        if c + 1 < len(categories):
            out = np.zeros(n)
            for f in range(s.folds):
                held = fold == f
                known, w = fit(~held & given, seen, y)
                out[held] = probability(logits(w, *_inner(known, *_rows_of(index, limits, held)), seen[held]))
            seen = np.column_stack([seen, out])
    return chain


def _rows_of(index: np.ndarray, limits: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    size = np.diff(limits)
    return index[np.repeat(rows, size)], np.concatenate([[0], np.cumsum(size[rows])])


def labelled_features(docs: DataFrame, labels: DataFrame, categories: dict[str, str], s: ChainSettings) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features and labels (NaN where unknown) of at most ``s.sample`` labelled documents, the first by a hash of their ids.

    Rows that repeat an id count once: by its largest labels, and by one of its texts, always the same.
    """
    names = list(categories)
    want = labels.select(F.col("doc_id").cast("long").alias("doc_id"), *[F.expr(x).cast("double").alias(c) for c, x in categories.items()])
    want = want.where(F.col("doc_id").isNotNull() & F.coalesce(*names).isNotNull())
    want = want.groupBy("doc_id").agg(*[F.max(c).alias(c) for c in names]).orderBy(F.xxhash64("doc_id"), "doc_id").limit(s.sample)

    def run(batches):
        for batch in batches:
            for i, j, data, at in text_blocks(batch.column("text")):
                index, limits = features(Block(data, at, NOT_WORD), s.buckets)
                sets = []
                for a, b in zip(limits[:-1], limits[1:]):
                    one = index[a:b]
                    if len(one) > s.sample_features:
                        first = np.argpartition(mix(one.astype(np.uint64), 31), s.sample_features)[: s.sample_features]
                        one = np.sort(one[first])
                    sets.append(one.astype(np.int32).tobytes())
                columns = [batch.column(c).slice(i, j - i) for c in ["doc_id", *names]]
                yield pa.RecordBatch.from_arrays([*columns, pa.array(sets, pa.binary())], ["doc_id", *names, "sets"])

    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    # at most s.sample rows of a few numbers each
    made = own.join(F.broadcast(want), "doc_id").mapInArrow(tidy(run), f"doc_id long, {', '.join(f'{c} double' for c in names)}, sets binary")
    # so few reach the driver, however many rows repeat an id
    rows = made.groupBy("doc_id", *names).agg(F.min("sets").alias("sets")).orderBy("doc_id").collect()
    sets = [np.frombuffer(r.sets, np.int32).astype(np.int64) for r in rows]
    limits = np.concatenate([[0], np.cumsum([len(x) for x in sets])]).astype(np.int64)
    known = np.array([[np.nan if r[c] is None else r[c] for c in names] for r in rows], float).reshape(len(rows), len(names))
    return (np.concatenate(sets) if sets else np.zeros(0, np.int64)), limits, known


#: In chain order; expressions over the label columns.
CATEGORIES = {"low_quality": "1 - quality", "toxic": "toxic"}


def fit_toxicity(docs: DataFrame, labels: DataFrame, categories: dict[str, str] | None = None, settings: ChainSettings = ChainSettings()) -> Chain:
    categories = categories or CATEGORIES
    return train_chain(*labelled_features(docs, labels, categories, settings), tuple(categories), settings)


def score_toxicity(spark: SparkSession, docs: DataFrame, chain: Chain) -> DataFrame:
    """``docs`` with a probability p_<category> for each category and ``rejected`` (the last reaches the threshold).

    A null or empty text has no features and is not rejected. All columns of ``docs`` stay; equal names are replaced.
    """
    held = spark.sparkContext.broadcast(chain)
    names = [f"p_{c}" for c in chain.categories]
    keep = [c for c in docs.columns if c not in [*names, "rejected"]]

    def run(batches):
        for batch in batches:
            for i, j, data, at in text_blocks(batch.column("text")):
                block = Block(data, at, NOT_WORD)
                index, limits = features(block, held.value.settings.buckets)
                p = held.value.predict(index, limits)
                rejected = (p[:, -1] >= held.value.settings.threshold) & (np.diff(limits) > 0)
                part = [batch.column(c).slice(i, j - i) for c in keep]
                yield pa.RecordBatch.from_arrays([*part, *[pa.array(p[:, k]) for k in range(len(names))], pa.array(rejected)], [*keep, *names, "rejected"])

    own = [StructField(c, DoubleType()) for c in names]
    schema = StructType([*[f for f in docs.schema if f.name in keep], *own, StructField("rejected", BooleanType())])
    return docs.select(*[F.col(f"`{c}`") for c in keep]).mapInArrow(tidy(run), schema)
