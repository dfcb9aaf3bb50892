"""Token counts without token ids.

Texts are cut into pre-tokens (a run of white space with the run of other characters after it); no pattern of the
tokenizer reaches across such a cut, so their counts add up. Every task asks the tokenizer once for each distinct pre-token
it meets, keeps the counts in a bounded table, and joins the table with the frequencies of each document's pre-tokens. Doing
that join inside the task moves no pre-token over the network: the distributed form would shuffle the corpus itself.
"""

from __future__ import annotations

import os
import re
from collections import Counter
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import text_blocks, tidy

#: Python counts 0x1C-0x1F as white space, the tokenizers do not.
CONTROL = re.compile(r"[\x1c-\x1f]")
PLAIN = re.compile(r"\s*\S+|\s+")
STRICT = re.compile(r"[^\S\x1c-\x1f]*[\S\x1c-\x1f]+|[^\S\x1c-\x1f]+")
#: Bounds of the table of counts in a task: entries, and characters of its keys.
MOST_ENTRIES, MOST_CHARS = 400_000, 16_000_000


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@lru_cache(2)
def load(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.no_truncation()
    tokenizer.no_padding()
    return tokenizer


def pre_tokens(text: str) -> list[str]:
    return (STRICT if CONTROL.search(text) else PLAIN).findall(text)


class PieceCounts:
    """Tokens per pre-token, asked for once each; forgets everything when it outgrows its bounds."""

    def __init__(self, path: str):
        self.tokenizer = load(path)
        self.known: dict[str, int] = {}
        self.chars = 0
        added = sorted((t.content for t in self.tokenizer.get_added_tokens_decoder().values()), key=len, reverse=True)
        self.special = re.compile("|".join(map(re.escape, added))) if added else None

    def frequencies(self, text: str) -> tuple[Counter, int]:
        """Pre-token frequencies of a text, and how many special strings stand in it."""
        if self.special is None or not self.special.search(text):
            return Counter(pre_tokens(text)), 0
        parts = self.special.split(text)
        total: Counter = Counter()
        for part in parts:
            total.update(pre_tokens(part))
        return total, len(parts) - 1

    def learn(self, tables: list[Counter]) -> None:
        new = list(set().union(*tables).difference(self.known))
        if len(self.known) + len(new) > MOST_ENTRIES or self.chars > MOST_CHARS:
            self.known.clear()
            self.chars = 0
            new = list(set().union(*tables))
        for k in range(0, len(new), 4096):
            part = new[k : k + 4096]
            for piece, made in zip(part, self.tokenizer.encode_batch_fast(part, add_special_tokens=False)):
                self.known[piece] = len(made.ids)
        self.chars += sum(map(len, new))

    def count(self, texts: list[str]) -> list[int]:
        tables = [self.frequencies(t) for t in texts]
        self.learn([t for t, _ in tables])
        known = self.known
        return [special + sum(known[piece] * n for piece, n in table.items()) for table, special in tables]


def token_counts(docs: DataFrame, path: str | None = None, limit: int = 512) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit per row; null texts are empty, other columns are ignored.

    Repeated rows and ids are counted row by row; an empty table gives an empty result.
    """
    path = path or vocabulary("byte_bpe_50k.json")

    def run(batches):
        counts = PieceCounts(path)
        for batch in batches:
            ids = batch.column("doc_id")
            for i, j, data, at in text_blocks(batch.column("text")):
                raw = data.tobytes()
                n = counts.count([raw[a:b].decode("utf-8", "replace") for a, b in zip(at[:-1], at[1:])])
                yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.array(np.diff(at)), pa.array(n, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    made = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), "doc_id long, n_bytes long, n_tokens long")
    return made.withColumn("over_limit", F.col("n_tokens") > limit)
