"""WARC archives with revisits, and their index merged from sorted runs.

A task writes its records as gzip members, one each, to files of bounded size in the shared folder, through the file system that the
folder's URI names (local, HDFS, S3, GCS, ...). Files count once the task that wrote them is done and has named them: what a lost or
repeated attempt leaves is never read. Readers go through a file member by member in pieces of bounded size, so neither a file nor a
payload is ever held whole. The place and length of every member are in the index, so that a capture can be fetched by itself.

Capture entries of each file form a sorted run; runs are dealt by key range and merged by a loser tree, which
gives capture histories in global order of URL key and time.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from datetime import datetime, timezone

import numpy as np
import pyarrow as pa
from pyarrow.fs import FileSystem
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import fresh_path, table
from .words import tidy

#: A file is closed once it has so many records or compressed bytes; readers and inflaters work in pieces of so many bytes.
FILE_RECORDS, FILE_BYTES, PIECE = 65_536, 64 << 20, 1 << 20
#: Entries of a key range that one task merges.
RANGE_ENTRIES = 200_000
END = b"\r\n\r\n"
EPOCH = 1_700_000_000


def digest_of(payload) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _with_digest(pages: DataFrame) -> DataFrame:
    def run(batches):
        for batch in batches:
            payloads = [x.as_buffer() for x in batch.column("html").cast(pa.large_string()).fill_null("").cast(pa.large_binary())]
            columns = [batch.column(c) for c in ("page_id", "url", "html")]
            columns += [pa.array([x.size for x in payloads], pa.int64()), pa.array([digest_of(x) for x in payloads], pa.string())]
            yield pa.RecordBatch.from_arrays(columns, ["page_id", "url", "html", "payload_bytes", "digest"])

    own = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return own.mapInArrow(tidy(run), "page_id long, url string, html string, payload_bytes long, digest string")


CONTROL = re.compile(r"[\x00-\x1f\x7f]")


def record_head(page_id: int | None, url: str | None, digest: str, size: int, latest: int | None, latest_url: str | None) -> bytes:
    """The header of a record; with ``latest`` that of a revisit of its payload."""
    safe = lambda u: CONTROL.sub(lambda m: f"%{ord(m[0]):02X}", u or "")
    date = lambda i: datetime.fromtimestamp(EPOCH + (i or 0) % 10**9, timezone.utc).strftime("%Y-%m-%dT%H:%M:%SZ")
    name = lambda i: f"<urn:page:{'' if i is None else i}>"
    lines = ["WARC/1.1", f"WARC-Type: {'response' if latest is None else 'revisit'}", f"WARC-Record-ID: {name(page_id)}", f"WARC-Date: {date(page_id)}"]
    lines += [f"WARC-Target-URI: {safe(url)}", f"WARC-Payload-Digest: sha1:{digest}"]
    if latest is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {name(latest)}"]
        lines += [f"WARC-Refers-To-Target-URI: {safe(latest_url)}", f"WARC-Refers-To-Date: {date(latest)}"]
    lines += [f"X-Payload-Length: {size}", "Content-Type: text/html; charset=utf-8", f"Content-Length: {size if latest is None else 0}"]
    return ("\r\n".join(lines) + "\r\n\r\n").encode()


def file_system(path: str) -> tuple[FileSystem, str]:
    system, folder = FileSystem.from_uri(path)
    return system, folder.rstrip("/")


def write_archives(spark: SparkSession, pages: DataFrame, path: str, least_bytes: int = 0) -> DataFrame:
    """One record per row; of equal payloads of at least ``least_bytes``, the largest page_id's is the response. Returns (file, records).

    A null page_id is written as an empty header value and is only a response where all its copies have none; it is then
    itself a response. Line ends and other control characters in a URL are percent-encoded.
    """
    rows = table(spark, _with_digest(pages).drop("html"), "digests")
    latest = rows.where("page_id is not null").groupBy("digest", "payload_bytes").agg(F.max("page_id").alias("latest"), F.max_by("url", "page_id").alias("latest_url"))
    # this join moves the payloads once; a digest that very many pages share can be divided, as both sides have an exchange
    latest = table(spark, latest, "latest")
    full = _with_digest(pages).join(latest, ["digest", "payload_bytes"], "left")
    revisit = (F.col("payload_bytes") >= least_bytes) & F.col("latest").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("latest"))
    full = full.select("page_id", "url", "html", "digest", "payload_bytes", F.when(revisit, F.col("latest")).alias("latest"), "latest_url")
    system, folder = file_system(path)
    system.create_dir(folder, recursive=True)

    def run(batches):
        system, folder = file_system(path)
        out, name, records, at, done = None, None, 0, 0, []
        for batch in batches:
            payloads = batch.column("html").cast(pa.large_string()).fill_null("").cast(pa.large_binary())
            heads = zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "digest", "payload_bytes", "latest", "latest_url")))
            for head, payload in zip(heads, payloads):
                if out is None:
                    name = f"part-{TaskContext.get().partitionId():05d}-{uuid.uuid4().hex}.warc.gz"
                    out, records, at = system.open_output_stream(f"{folder}/{name}", compression=None), 0, 0
                packer = zlib.compressobj(6, zlib.DEFLATED, 31)
                parts = [record_head(*head), END] if head[4] is not None else [record_head(*head), payload.as_buffer(), END]
                for part in parts:
                    at += out.write(packer.compress(part))
                at += out.write(packer.flush())
                records += 1
                if records >= FILE_RECORDS or at >= FILE_BYTES:
                    out.close()
                    done.append((name, records))
                    out = None
        if out is not None:
            out.close()
            done.append((name, records))
        yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in done], pa.string()), pa.array([d[1] for d in done], pa.int64())], ["file", "records"])

    return table(spark, full.mapInArrow(tidy(run), "file string, records long"), "files")


HEADER = re.compile(rb"([^:\r\n]+):[ \t]*([^\r\n]*)\r\n")
#: A header longer than this is not one.
MOST_HEADER = 1 << 20


class Record:
    """A record as its bytes come in: its headers, and its block's length and digest, or the block itself if ``keep``."""

    def __init__(self, keep: bool = False):
        self.head, self.headers = bytearray(), None
        self.left = 0
        self.hash, self.block, self.tail = hashlib.sha1(), bytearray() if keep else None, bytearray()

    def take(self, data: bytes) -> None:
        if self.headers is None:
            self.head += data
            end = self.head.find(END)
            if end < 0:
                if len(self.head) > MOST_HEADER:
                    raise ValueError("no WARC header")
                return
            lines, data = bytes(self.head[: end + 2]), bytes(self.head[end + 4 :])
            if not lines.startswith(b"WARC/"):
                raise ValueError("no WARC record")
            found = HEADER.findall(lines, lines.index(b"\r\n") + 2)
            self.headers = {k.decode().lower(): v.decode("utf-8", "replace") for k, v in found}
            self.size = self.left = int(self.headers["content-length"])
            self.head = bytearray()
        block, rest = data[: self.left], data[self.left :]
        self.left -= len(block)
        self.hash.update(block)
        if self.block is not None:
            self.block += block
        self.tail += rest

    def finish(self) -> Record:
        if self.headers is None or self.left or self.tail != END:
            raise ValueError("record does not end where its length says")
        return self

    @property
    def digest(self) -> str:
        return base64.b32encode(self.hash.digest()).decode()


def members(stream, keep: bool = False) -> Iterator[tuple[int, int, Record]]:
    """(offset, compressed length, record) of every gzip member, read and inflated piece by piece."""
    at, data = 0, stream.read(PIECE)
    while data:
        inflate, record, begin = zlib.decompressobj(31), Record(keep), at
        while not inflate.eof:
            if not data:
                data = stream.read(PIECE)
                if not data:
                    raise ValueError(f"member at {begin} breaks off")
            record.take(inflate.decompress(data, PIECE))
            left = inflate.unused_data if inflate.eof else inflate.unconsumed_tail
            at += len(data) - len(left)
            data = left
        yield begin, at - begin, record.finish()
        data = data or stream.read(PIECE)


def fetch(path: str, file: str, offset: int, length: int) -> tuple[dict[str, str], bytes]:
    """Headers and block of the one record that an index entry names; no other bytes of the file are read."""
    system, folder = file_system(path)
    with system.open_input_file(f"{folder}/{file}") as f:
        f.seek(offset)
        _, _, record = next(members(pa.BufferReader(f.read(length)), keep=True))
    return record.headers, bytes(record.block)


def url_key(url: str) -> str:
    """Host labels in reverse order, then path and query, lower-cased: URLs of a site sort together."""
    rest = url.partition("://")[2] or url
    host, slash, tail = rest.partition("/")
    host = host.partition("?")[0].partition("#")[0].partition(":")[0].lower()
    return ",".join(reversed(host.removeprefix("www.").split("."))) + ")/" + tail.partition("#")[0].lower()


CAPTURE = "url_key string, captured string, file string, offset long, length long, page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, sound boolean"
KINDS = [pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.bool_()]


def read_captures(spark: SparkSession, path: str, files: DataFrame) -> DataFrame:
    """A run per file: its capture entries, sorted by URL key and time. ``offset`` and ``length`` are those of the record's gzip
    member in the file. ``sound``: the payload's digest and length hold."""

    def number(name: str) -> int | None:
        value = name.rpartition(":")[2].rstrip(">")
        return int(value) if value else None

    def run(batches):
        system, folder = file_system(path)
        for batch in batches:
            for file in batch.column("file").to_pylist():
                rows = []
                with system.open_input_stream(f"{folder}/{file}", compression=None) as stream:
                    for offset, length, r in members(stream):
                        h = r.headers
                        response = h["warc-type"] == "response"
                        digest = h["warc-payload-digest"].removeprefix("sha1:")
                        n = r.size if response else int(h["x-payload-length"])
                        refers = None if response else number(h["warc-refers-to"])
                        place = (url_key(h["warc-target-uri"]), h["warc-date"], file, offset, length)
                        sound = not response or r.digest == digest
                        rows.append((*place, number(h["warc-record-id"]), n, digest, h["warc-type"], refers, sound))
                rows.sort(key=lambda r: r[:4])
                columns = list(zip(*rows)) if rows else [()] * len(KINDS)
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, KINDS)], [c.split()[0] for c in CAPTURE.split(", ")])

    # a task for every few files: names are few bytes and much work
    tasks = max(1, min(files.count(), 8 * spark.sparkContext.defaultParallelism, 10_000))
    return files.select("file").repartition(tasks, "file").mapInArrow(tidy(run), CAPTURE)


class LoserTree:
    """Merges sorted runs: every inner node keeps the loser of its last match, so a step costs one path of matches."""

    def __init__(self, runs: list[Iterator]):
        self.runs = [iter(r) for r in runs]
        self.k = max(1, len(self.runs))
        self.heads = [next(r, None) for r in self.runs] or [None]
        self.losers = [-1] * self.k
        self.winner = self._build(1) if self.k > 1 else 0

    def _before(self, a: int, b: int) -> bool:
        x, y = self.heads[a], self.heads[b]
        if x is None or y is None:
            return y is None and (x is not None or a < b)
        return (x, a) < (y, b)

    def _build(self, node: int) -> int:
        if node >= self.k:
            return node - self.k
        a, b = self._build(2 * node), self._build(2 * node + 1)
        if not self._before(a, b):
            a, b = b, a
        self.losers[node] = b
        return a

    def __iter__(self):
        while self.heads[self.winner] is not None:
            yield self.heads[self.winner]
            w = self.winner
            self.heads[w] = next(self.runs[w], None)
            node = (w + self.k) // 2
            while node >= 1 and self.k > 1:
                if self._before(self.losers[node], w):
                    self.losers[node], w = w, self.losers[node]
                node //= 2
            self.winner = w


def merge_index(spark: SparkSession, runs: DataFrame, n_entries: int) -> DataFrame:
    """Capture entries in global order: partitions are key ranges, each merged from the runs that reach it.

    ``history_rank`` counts the captures of a URL key from 1. Times break ties of a key, file and offset those of a time; a URL of
    very many captures spreads over ranges, as the ranges are cut by key and time.
    """
    parts = max(1, -(-n_entries // RANGE_ENTRIES), min(spark.sparkContext.defaultParallelism, n_entries // 1000))
    order = ["url_key", "captured", "file", "offset"]
    dealt = runs.repartitionByRange(parts, *order)
    names = [c.split()[0] for c in CAPTURE.split(", ")]

    def run(batches):
        parts = [b for b in batches if b.num_rows]
        if not parts:
            return
        whole = pa.Table.from_batches(parts)
        keys = list(zip(*[whole.column(c).to_pylist() for c in order]))
        # fetched map outputs stand one after another; each is in order, so a run ends where the order falls
        breaks = [0, *[i for i in range(1, len(keys)) if keys[i] < keys[i - 1]], len(keys)]
        tree = LoserTree([((keys[i], i) for i in range(a, b)) for a, b in zip(breaks, breaks[1:])])
        take = np.fromiter((i for _, i in tree), np.int64, len(keys))
        yield from whole.take(pa.array(take)).combine_chunks().to_batches()

    return dealt.select(*names).mapInArrow(tidy(run), CAPTURE)


def archive(spark: SparkSession, pages: DataFrame, path: str | None = None, least_bytes: int = 0) -> DataFrame:
    """Write ``pages``, read the archives back and return the merged index: one row per record, that is, per page row.

    Null html is an empty payload, a null URL an empty target. An empty table gives an empty index. Rows that repeat a page_id
    are records of their own; those of equal payload and the largest id are all responses. Other columns are ignored.
    """
    path = path or fresh_path(spark, "warc")
    files = write_archives(spark, pages, path, least_bytes)
    runs = table(spark, read_captures(spark, path, files), "captures")
    n = runs.count()
    return merge_index(spark, runs, n)
