"""Web archives: WARC records, capture index runs, and their external merge into global histories.

Writing. Each task writes its pages as gzip members of rolling archive files in a shared folder, one
member a record, and beside each file a locally sorted run of its captures. Files of a failed attempt are
named by no run row, so they do no harm.

Merging. The runs are dealt out by ranges of (URL key, timestamp, page), which splits even one URL's
captures; in each range the runs' parts, each in order, are merged by a tree of losers. The parts of one
range are all a task holds (`RANGE_BYTES`), so the whole index is never in one place.

Reading. The merged captures are dealt out by archive stretch, read at their offsets in rising order,
unpacked and parsed; what is returned comes from the records themselves.

Of records with equal payloads of at least `least` bytes, the one with the smallest page id is a response
and the others revisit it; they carry no payload but its digest and length.

Defined results: a null payload is an empty one; a null URL has an empty URL key; rows that repeat a page
id are records of their own (equal ones with the smallest id are all responses); a null page id is kept
and is never referred to (with no other holder of its payload it is a response).
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import os
import zlib
from collections.abc import Callable, Iterator
from urllib.parse import quote, unquote, urlsplit

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shoal.core.storage import Scratch, shared_folder
from shoal.llm.storage import arrow_stage, input_bytes

#: Records and bytes after which a task begins a new archive file; bytes of index that one merge task takes.
FILE_RECORDS, FILE_BYTES, RANGE_BYTES = 50_000, 512 << 20, 16 << 20
STRETCH = 4 << 20
RUNS = "run string, urlkey string, captured string, page_id long, file string, offset long, size long"
_COLUMNS = [c.split()[0] for c in RUNS.split(", ")]


def _open(uri: str, mode: str):
    """A file in the shared folder: a plain path, or any store that Arrow can open."""
    if uri.startswith(("file:", "/")):
        path = urlsplit(uri).path
        if mode == "wb":
            os.makedirs(os.path.dirname(path), exist_ok=True)
        return open(path, mode)
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri)
    return store.open_output_stream(path) if mode == "wb" else store.open_input_file(path)


def url_key(url: str | None) -> str:
    """Reversed host labels, then path and query, lower-cased: neighbours in a site are neighbours in order."""
    if not url:
        return ""
    rest = url.lower().partition("://")[2] or url.lower()
    host, slash, path = rest.partition("/")
    return ",".join(reversed(host.split("."))) + ")" + slash + path


def digest32(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page: int | None, url: str | None, captured: str, payload: bytes, refers_to: int | None) -> bytes:
    """One WARC record, response or (with refers_to) revisit."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    lines = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'' if page is None else page}>", f"WARC-Date: {captured}", f"WARC-Target-URI: {quote(url or '', safe=':/?#[]@!$&()*+,;=%')}", f"WARC-Payload-Digest: sha1:{digest32(payload)}", "Content-Type: application/http; msgtype=response"]
    body = http
    if refers_to is None:
        body += payload
    else:
        lines += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    lines.append(f"Content-Length: {len(body)}")
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def parse(data: bytes) -> tuple[int | None, int, str, str, int | None]:
    """page id, payload bytes, payload digest, record type, refers-to of a record; checks length and digest."""
    head, _, rest = data.partition(b"\r\n\r\n")
    field = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    body = rest[: int(field["Content-Length"])]
    if rest[len(body) :] != b"\r\n\r\n":
        raise ValueError("a record's length does not fit")
    http, _, payload = body.partition(b"\r\n\r\n")
    page = _page(field["WARC-Record-ID"])
    digest = field["WARC-Payload-Digest"].partition(":")[2]
    if field["WARC-Type"] == "revisit":
        size = int(next(x.partition(b":")[2] for x in http.split(b"\r\n") if x.lower().startswith(b"content-length")))
        return page, size, digest, "revisit", _page(field["WARC-Refers-To"])
    if digest32(payload) != digest:
        raise ValueError("a payload does not fit its digest")
    return page, len(payload), digest, "response", None


def _page(urn: str) -> int | None:
    name = unquote(urn.strip("<>").rpartition(":")[2])
    return int(name) if name else None


class _Archive:
    """One archive file being written, and its run."""

    def __init__(self, folder: str) -> None:
        task = TaskContext.get()
        self.stem, self.n = f"{folder}/part-{task.partitionId():06d}-{task.taskAttemptId()}", 0
        self.out, self.rows, self.at = None, [], 0

    def add(self, page, url, captured, payload, refers_to) -> None:
        if self.out is None:
            self.name, self.rows, self.at = f"{self.stem}-{self.n:04d}.warc.gz", [], 0
            self.n += 1
            self.out = _open(self.name, "wb")
        member = gzip.compress(record(page, url, captured, payload, refers_to), 4, mtime=0)
        self.out.write(member)
        self.rows.append((self.name, url_key(url), captured, page, self.name, self.at, len(member)))
        self.at += len(member)

    def full(self) -> bool:
        return self.out is not None and (len(self.rows) >= FILE_RECORDS or self.at >= FILE_BYTES)

    def close(self) -> Iterator[pa.RecordBatch]:
        if self.out is not None:
            self.out.close()
            self.out = None
            self.rows.sort(key=_order)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*self.rows, strict=True), _TYPES, strict=True)], _COLUMNS)


_TYPES = [pa.string(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64()]


def _order(row: tuple) -> tuple:
    return row[1], row[2], row[3] is not None, row[3] or 0, row[4], row[5]


def write_archives(pages: DataFrame, scratch: Scratch, least: int = 0, key: str = "page_id", url: str = "url", payload: str = "html", captured: Column | None = None) -> DataFrame:
    """Writes the pages as archives; returns the locally sorted runs, as a written table."""
    folder = shared_folder(pages.sparkSession, "warc")
    body = F.coalesce(F.col(payload).cast("binary"), F.lit(b""))
    rows = pages.select(F.col(key).cast("long").alias("page"), F.col(url).alias("url"), F.coalesce(captured if captured is not None else F.lit(None).cast("string"), F.lit("2000-01-01T00:00:00Z")).alias("captured"), body.alias("body"), F.sha1(body).alias("sha"))
    first = pages.select(F.sha1(body).alias("same"), F.col(key).cast("long").alias("page")).groupBy("same").agg(F.min("page").alias("first"))
    rows = rows.join(first, F.col("sha") == F.col("same"), "left").withColumn("first", F.when((F.octet_length("body") >= least) & ~F.col("page").eqNullSafe(F.col("first")), F.col("first")))

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        archive = _Archive(folder)
        for b in batches:
            for page, address, when, data, refers_to in zip(*(b.column(i) for i in range(5)), strict=True):
                archive.add(page.as_py(), address.as_py(), when.as_py(), data.as_py(), refers_to.as_py())
                if archive.full():
                    yield from archive.close()
        yield from archive.close()

    return scratch.write(arrow_stage(rows, ["page", "url", "captured", "body", "first"], write, RUNS))


class LoserTree:
    """Merges sorted iterators: each inner node keeps the loser of its match, so a step replays one path."""

    def __init__(self, streams: list[Iterator], order: Callable) -> None:
        self.streams, self.order, self.k = streams, order, len(streams)
        self.head = [None] * self.k
        self.key: list = [None] * self.k
        self.loser = [-1] * self.k
        for i in range(self.k):
            self._next(i)
        self.winner = self._build(1) if self.k > 1 else 0

    def _next(self, i: int) -> None:
        self.head[i] = next(self.streams[i], None)
        self.key[i] = None if self.head[i] is None else self.order(self.head[i])

    def _before(self, a: int, b: int) -> bool:
        """An exhausted stream loses; equal keys go by stream."""
        if self.key[a] is None or self.key[b] is None:
            return self.key[b] is None and (self.key[a] is not None or a < b)
        return (self.key[a], a) < (self.key[b], b)

    def _build(self, node: int) -> int:
        if node >= self.k:
            return node - self.k
        a, b = self._build(2 * node), self._build(2 * node + 1)
        win, lose = (a, b) if self._before(a, b) else (b, a)
        self.loser[node] = lose
        return win

    def __iter__(self) -> Iterator:
        while self.k and self.head[self.winner] is not None:
            yield self.head[self.winner]
            now = self.winner
            self._next(now)
            node = (now + self.k) // 2
            while node >= 1:
                if self._before(self.loser[node], now):
                    self.loser[node], now = now, self.loser[node]
                node //= 2
            self.winner = now


def merge_runs(runs: DataFrame) -> DataFrame:
    """All captures in the global order of (URL key, timestamp, page): by ranges, and in each range by a loser tree."""
    ranges = max(2 * runs.sparkSession.sparkContext.defaultParallelism, input_bytes(runs) // RANGE_BYTES + 1)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: dict[str, list[tuple]] = {}
        for b in batches:
            for row in zip(*(b.column(i).to_pylist() for i in range(7)), strict=True):
                parts.setdefault(row[0], []).append(row)
        streams = []
        for name in sorted(parts):
            rows = parts[name]
            if any(_order(a) > _order(b) for a, b in zip(rows, rows[1:], strict=False)):
                rows.sort(key=_order)  # the shuffle may hand a run's stretches over in another order
            streams.append(iter(rows))
        held: list[tuple] = []
        for row in LoserTree(streams, _order):
            held.append(row)
            if len(held) == 20_000:
                yield _rows(held)
                held = []
        if held:
            yield _rows(held)

    by_range = runs.repartitionByRange(int(ranges), "urlkey", "captured", "page_id", "file", "offset")
    return by_range.mapInArrow(merge, RUNS)


def _rows(held: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held, strict=True), _TYPES, strict=True)], _COLUMNS)


def read_records(captures: DataFrame) -> DataFrame:
    """The records of captures, read at their places: page_id, payload_bytes, payload_digest, record_type, refers_to, urlkey, captured."""
    schema = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, urlkey string, captured string"

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name, source = None, None
        for b in batches:
            out = []
            for file, offset, size, key, when in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                if file != name:
                    if source is not None:
                        source.close()
                    name, source = file, _open(file, "rb")
                source.seek(offset)
                out.append((*parse(zlib.decompress(source.read(size), 31)), key, when))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(kinds)], [c.split()[0] for c in schema.split(", ")])
        if source is not None:
            source.close()

    stretch = captures.select("file", "offset", "size", "urlkey", "captured").repartition("file", F.floor(F.col("offset") / STRETCH))
    return stretch.sortWithinPartitions("file", "offset").mapInArrow(read, schema)


def archive_round_trip(pages: DataFrame, least: int = 0, key: str = "page_id", url: str = "url", payload: str = "html") -> DataFrame:
    """Writes the archives, merges their index, and reads every record back."""
    scratch = Scratch(pages.sparkSession, "captures")
    runs = write_archives(pages, scratch, least, key, url, payload)
    return read_records(scratch.write(merge_runs(runs)))
