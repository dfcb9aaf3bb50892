"""Line-first cleaning: judge every line, drop those that fail, then reject documents that lose too much.

A line fails if it shows no sentence end (punctuation), if it is mostly menu separators (navigation), or if it is a
known notice (boilerplate). Word and repetition counts of whole texts are taken from the bytes of many texts at once.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import Block, mix, text_blocks, tidy

EXACT = np.arange(1, 257, dtype=np.uint64)
SYMBOL = np.zeros(256, bool)
SYMBOL[list(b"#*$%&|<>")] = True
#: A sentence end: its mark, then closing quotes or brackets, then white space or the line's end.
SENTENCE_END = re.compile(r"""[.!?…。！？]["'”’»)\]]*(?:[\x20\x09-\x0D]|$)""")
BOILERPLATE = re.compile(
    r"lorem ipsum|all rights reserved|terms of (?:use|service)|privacy policy|cookie policy|accept (?:all )?cookies|enable javascript"
    r"|sign up for our newsletter|click here to|skip to (?:main )?content"
    r"|alle rechte vorbehalten|datenschutzerklärung|tous droits réservés|politique de confidentialité|todos los derechos reservados|política de privacidad",
    re.IGNORECASE,
)
#: Separators per word from which a line of three words or more counts as navigation.
MENU_SHARE = 0.25
#: Boilerplate is a short notice; a longer line that mentions one is prose.
NOTICE_WORDS = 30
#: The least share of a document's words that must stand in lines that pass.
LEAST_KEPT = 0.3


def line_failure(line: str, n_words: int) -> str | None:
    """Which rule a line with words fails, if any."""
    if n_words >= 3 and line.count(" | ") + line.count(" » ") + line.count(" > ") >= MENU_SHARE * n_words:
        return "navigation"
    if n_words <= NOTICE_WORDS and BOILERPLATE.search(line):
        return "boilerplate"
    if not SENTENCE_END.search(line):
        return "punctuation"
    return None


WORD = re.compile(r"[^\x20\x09-\x0D]+")


def clean_lines(text: str) -> tuple[str, int, int, int]:
    """The text without failing lines; words of all lines and of those kept; lines that repeat an earlier one."""
    kept, seen, words, good, repeats = [], set(), 0, 0, 0
    for line in text.split("\n"):
        n = len(line.split()) if line.isascii() and not _CONTROL(line) else len(WORD.findall(line))
        if n:
            if line in seen:
                repeats += 1
            else:
                seen.add(line)
            words += n
            if line_failure(line, n):
                continue
            good += n
        kept.append(line)
    return "\n".join(kept), words, good, repeats


_CONTROL = re.compile(r"[\x1c-\x1f]").search


def repeated_words(block: Block, word: np.ndarray, window: int = 5) -> np.ndarray:
    """Per text: words covered by windows of ``window`` words that occur in the text at least twice."""
    n, count = len(word), block.counts
    covered = np.zeros(n + 1, np.int64)
    if n >= window:
        owner = np.repeat(np.arange(len(count)), count)
        rolled = mix(owner[: n - window + 1].astype(np.uint64), 5)
        for k in range(window):
            rolled = rolled * np.uint64(0xD6E8FEB86659FD93) + word[k : n - window + 1 + k]
        inside = np.flatnonzero(owner[: n - window + 1] == owner[window - 1 :])
        rolled = mix(rolled[inside])
        order = np.argsort(rolled, kind="stable")
        ranked = rolled[order]
        twin = np.zeros(len(ranked), bool)
        twin[1:] = ranked[1:] == ranked[:-1]
        twin[:-1] |= twin[1:]
        at = inside[order[twin]]
        np.add.at(covered, at, 1)
        np.add.at(covered, at + window, -1)
    total = np.concatenate([[0], np.cumsum(np.cumsum(covered[:n]) > 0)])
    return total[block.first[1:]] - total[block.first[:-1]]


SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, words_kept long, clean_text string"


def line_first_cleaning(docs: DataFrame, least_words: int = 10, most_repeated: int = 20, with_text: bool = True) -> DataFrame:
    """Counts, verdicts and the cleaned text of every document, in one pass without a shuffle.

    Null and empty texts have no words and fail. Repeated rows are judged row by row; other columns are ignored.
    """

    def run(batches):
        for batch in batches:
            ids = batch.column("doc_id")
            for i, j, data, at in text_blocks(batch.column("text")):
                block = Block(data, at)
                per_text = lambda mask: (lambda t: t[at[1:]] - t[at[:-1]])(np.concatenate([[0], np.cumsum(mask)]))
                starts_char = (data & 0xC0) != 0x80
                gap = (data == 0x20) | ((data >= 0x09) & (data <= 0x0D))
                raw = data.tobytes()
                lines = [clean_lines(raw[a:b].decode("utf-8", "replace")) for a, b in zip(at[:-1], at[1:])]
                clean, _, good, repeats = zip(*lines)
                columns = [ids.slice(i, j - i), pa.array(block.counts), pa.array(per_text(starts_char & ~gap)), pa.array(per_text(SYMBOL[data]))]
                columns += [pa.array(repeats, pa.int64()), pa.array(repeated_words(block, block.hashes(EXACT))), pa.array(good, pa.int64())]
                columns.append(pa.array(clean if with_text else [None] * len(clean), pa.string()))
                yield pa.RecordBatch.from_arrays(columns, [c.split()[0] for c in SCHEMA.split(", ")])

    made = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), SCHEMA)
    made = made.withColumn("base_failed", (F.col("n_words") < least_words) | (100 * F.col("n_repeat_words") > most_repeated * F.col("n_words")))
    return made.withColumn("kept", ~F.col("base_failed") & (F.col("words_kept") >= LEAST_KEPT * F.col("n_words")))
