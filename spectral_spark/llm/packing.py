"""Best-fit packing of token sequences with a bounded number of open bins.

Each task keeps at most ``open_bins`` bins. A bitset keyed by free space finds the tightest bin that still fits; when too many
are open, the fullest is closed. Pieces are offered block by block, longest first. Bins that are still open when a task's rows
end are packed once more with those of other tasks, as wholes, so that many small tasks do not leave many half-empty bins.
"""

from __future__ import annotations

import re
import zlib
from collections import defaultdict
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import table
from .tokens import CONTROL, MOST_CHARS, load, vocabulary
from .words import text_blocks, tidy

STRICT_WORDS = re.compile(r"[\S\x1c-\x1f]+")
#: Bound of a worker's table of ids.
MOST_WORDS = 700_000
#: Text bytes that are encoded together.
ENCODE_BYTES = 2 << 20
#: Bins left by this many tasks are packed together in the second pass, with this many times as many open bins as the first:
#: its items are whole bins, so the bound costs no memory worth naming and few bins are closed before their time.
TASKS_TOGETHER, TAIL_BINS = 64, 8


class BestFit:
    """Bounded-space online best fit; ``put`` gives (bin number, offset)."""

    def __init__(self, capacity: int, open_bins: int):
        self.capacity, self.open_bins = capacity, open_bins
        self.free_bits = 0
        self.by_free: dict[int, list[int]] = defaultdict(list)
        self.n_open = self.made = 0

    def _take(self, free: int) -> int:
        at = self.by_free[free]
        bin_ = at.pop()
        if not at:
            self.free_bits ^= 1 << free
        return bin_

    def put(self, length: int) -> tuple[int, int]:
        fitting = self.free_bits >> length
        if fitting:
            free = length + (fitting & -fitting).bit_length() - 1
            bin_ = self._take(free)
        else:
            if self.n_open >= self.open_bins:
                self._take((self.free_bits & -self.free_bits).bit_length() - 1)
                self.n_open -= 1
            free, bin_ = self.capacity, self.made
            self.made += 1
            self.n_open += 1
        left = free - length
        if left:
            self.by_free[left].append(bin_)
            self.free_bits |= 1 << left
        else:
            self.n_open -= 1
        return bin_, self.capacity - free

    def still_open(self) -> set[int]:
        return {b for at in self.by_free.values() for b in at}


#: The tokenizer's pre-tokens of lower-cased text within U+00FF; other texts are cut at white space alone.
PRE_TOKEN = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zªµºß-öø-ÿ]+|[0-9²³¹¼-¾]|[^a-zªµºß-öø-ÿ0-9²³¹¼-¾\x09-\x0d \x85\xa0]+")
BEYOND = re.compile(r"[^\x00-\xff]")


class WordIds(dict):
    """Ids of pre-tokens, asked of the tokenizer once each, in flat arrays."""

    def __init__(self, path: str):
        super().__init__()
        self.tokenizer = load(path)
        self.reset()

    def reset(self) -> None:
        self.clear()
        self.new: list[str] = []
        self.chars = self.used = 0
        self.flat = np.empty(1 << 16, np.uint32)
        # where the ids of each word begin; the end of the last one follows
        self.start = np.zeros(1 << 16, np.int64)
        self.learned = 0

    def __missing__(self, word: str) -> int:
        self[word] = k = len(self)
        self.new.append(word)
        self.chars += len(word)
        return k

    def _learn(self) -> None:
        for k in range(0, len(self.new), 4096):
            made = [e.ids for e in self.tokenizer.encode_batch_fast(self.new[k : k + 4096], add_special_tokens=False)]
            sizes = np.array([len(x) for x in made], np.int64)
            ids = np.fromiter((i for x in made for i in x), np.uint32, int(sizes.sum()))
            while self.used + len(ids) > len(self.flat):
                self.flat = np.concatenate([self.flat, np.empty_like(self.flat)])
            self.flat[self.used : self.used + len(ids)] = ids
            end = self.learned + len(made)
            if end >= len(self.start):
                self.start = np.concatenate([self.start, np.empty(max(len(self.start), len(made)), np.int64)])
            self.start[self.learned + 1 : end + 1] = self.used + np.cumsum(sizes)
            self.learned = end
            self.used += len(ids)
        self.new = []

    def encode(self, texts: list[str], end_id: int) -> list[np.ndarray]:
        """Ids of every text, ``end_id`` added."""
        if len(self) > MOST_WORDS or self.chars > MOST_CHARS:
            self.reset()
        codes = []
        for text in texts:
            words = cut(text)
            codes.append(np.fromiter(map(self.__getitem__, words), np.int64, len(words)))
        self._learn()
        out = []
        for code in codes:
            size = self.start[code + 1] - self.start[code]
            end = np.cumsum(size)
            n = int(end[-1]) if len(end) else 0
            ids = np.empty(n + 1, np.uint32)
            ids[:n] = self.flat[np.arange(n) + np.repeat(self.start[code] - (end - size), size)]
            ids[n] = end_id
            out.append(ids)
        return out


def cut(text: str) -> list[str]:
    """Parts of a text that the tokenizer treats apart: their ids, joined, are the text's."""
    if BEYOND.search(text) or "<|" in text:
        return STRICT_WORDS.findall(text) if CONTROL.search(text) else text.split()
    return PRE_TOKEN.findall(text.lower())


@lru_cache(2)
def shared_ids(path: str) -> WordIds:
    """Kept by a worker process between its tasks."""
    return WordIds(path)


PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, bin long, offset long, task long, is_open boolean"


def pack(spark: SparkSession, docs: DataFrame, path: str | None = None, capacity: int = 4096, open_bins: int = 256, end_id: int = 1) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null and empty texts are a document of ``end_id`` alone. Rows that repeat a doc_id are packed as documents of their own.
    Documents longer than ``capacity`` are cut into full pieces and a last, shorter one. Other columns are ignored.
    """
    path = path or vocabulary("word_bpe_49k.json")

    def run(batches):
        words, bins, task = shared_ids(path), BestFit(capacity, open_bins), TaskContext.get().partitionId()
        held: list[tuple] = []
        for batch in batches:
            doc_ids = batch.column("doc_id")
            for i, j, data, at in text_blocks(batch.column("text"), ENCODE_BYTES):
                raw = data.tobytes()
                ids = words.encode([raw[a:b].decode("utf-8", "replace") for a, b in zip(at[:-1], at[1:])], end_id)
                names = doc_ids.slice(i, j - i).to_pylist()
                pieces = [(len(part := x[s : s + capacity]), names[k], s // capacity, s, zlib.crc32(part.astype("<u4").tobytes())) for k, x in enumerate(ids) for s in range(0, len(x), capacity)]
                pieces.sort(key=lambda x: -x[0])
                for n, name, piece, s, crc in pieces:
                    bin_, offset = bins.put(n)
                    held.append((name, piece, s, n, crc, bin_, offset))
            # rows of closed bins need not be held
            open_now = bins.still_open()
            yield _rows([x for x in held if x[5] not in open_now], task, False)
            held = [x for x in held if x[5] in open_now]
        yield _rows(held, task, True)

    first = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), PIECES)
    first = table(spark, first, "pieces")
    tails = first.where("is_open").groupBy("task", "bin").agg(F.sum("length").alias("used"))

    def again(t: pa.Table) -> pa.Table:
        t = t.sort_by([("used", "descending"), ("task", "ascending"), ("bin", "ascending")])
        bins = BestFit(capacity, open_bins * TAIL_BINS)
        placed = [bins.put(n) for n in t.column("used").to_pylist()]
        group = t.column("task")[0].as_py() // TASKS_TOGETHER if t.num_rows else 0
        to, base = pa.array([-1 - (group << 32) - b for b, _ in placed], pa.int64()), pa.array([o for _, o in placed], pa.int64())
        return pa.table({"task": t.column("task"), "bin": t.column("bin"), "to": to, "base": base})

    moved = tails.groupBy(F.expr(f"task div {TASKS_TOGETHER}")).applyInArrow(again, "task long, bin long, to long, base long")
    own = F.expr("shiftleft(task, 32) + bin")
    cols = ["doc_id", "piece", "start", "length", "ids_crc32"]
    closed = first.where("not is_open").select(*cols, own.alias("sequence_id"), "offset")
    joined = first.where("is_open").join(moved, ["task", "bin"]).select(*cols, F.col("to").alias("sequence_id"), (F.col("offset") + F.col("base")).alias("offset"))
    return closed.unionByName(joined)


def _rows(rows: list[tuple], task: int, is_open: bool) -> pa.RecordBatch:
    columns = list(zip(*rows)) if rows else [()] * 7
    kinds = [pa.int64(), pa.int32(), *[pa.int64()] * 5]
    arrays = [pa.array(c, k) for c, k in zip(columns, kinds)]
    arrays += [pa.array([task] * len(rows), pa.int64()), pa.array([is_open] * len(rows), pa.bool_())]
    return pa.RecordBatch.from_arrays(arrays, ["doc_id", "piece", "start", "length", "ids_crc32", "bin", "offset", "task", "is_open"])
