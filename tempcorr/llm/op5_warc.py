"""WARC archives with revisits, and a capture index in global order.

Records are made by SQL expressions and written by Spark's text writer, whose record separator is the blank line that
ends a WARC record: gzip files, in any store that Spark writes, committed by its protocol. The archives are then read back
and parsed; every file gives a run of index entries sorted by URL key and time. Runs are dealt by ranges of the key and
time and merged by a loser tree of k runs in each range, so that the whole is in order.

Defined results: null html is an empty payload, null url a record without a target, null page_id a record of its own that
is older than those with an id; repeated page_ids are records of their own, each judged by its own payload; an empty table
gives an empty index; other columns are ignored, whatever their names. A reader holds a file of at most RECORDS records,
so that very long pages need memory for as many of them.
"""

from __future__ import annotations

import gzip
import hashlib
import tempfile
import uuid
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tempcorr.llm.common import lean, partitions, shared_folder, written

CRLF = "\r\n"
INDEX = "urlkey string, captured string, page_id long, record_type string, refers_to long, payload_bytes long, payload_digest string, run string, place long"
#: Records of a file: bounds what a reader holds.
RECORDS = 2000
ID, NO_ID = "urn:tempcorr:page:", "none"
#: Rows of a run that are read from disk at once, and runs that are merged at once.
BLOCK, FAN = 128, 256


def records(pages: DataFrame, least: int = 1000) -> DataFrame:
    """(value): one WARC record for every page. Of equal payloads of `least` bytes the one of the largest page_id is whole."""
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    known = pages.select("page_id", F.octet_length("html").alias("size"), F.sha1(F.col("html").cast("binary")).alias("digest"))
    last = known.where(F.col("size") >= least).groupBy("digest").agg(F.max("page_id").alias("last"), F.count("*").alias("n")).where("n > 1")
    revisits = known.where(F.col("size") >= least).join(last, "digest").where("page_id is null and last is not null or page_id < last").select(F.col("page_id").alias("_page"), F.col("digest").alias("_digest"), "last").distinct()
    full = pages.withColumn("size", F.octet_length("html")).withColumn("digest", F.sha1(F.col("html").cast("binary")))
    full = full.join(revisits, F.col("page_id").eqNullSafe(F.col("_page")) & (F.col("digest") == F.col("_digest")), "left")
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), F.col("size").cast("string"), F.lit(CRLF + CRLF))
    again = F.col("last").isNotNull()
    block = F.when(again, http).otherwise(F.concat(http, F.col("html")))
    url = F.regexp_replace("url", r"[\x00-\x20\x7f]", "%20")

    def field(name: str, value: Column) -> Column:
        return F.coalesce(F.concat(F.lit(f"{name}: "), value, F.lit(CRLF)), F.lit(""))

    page = F.coalesce(F.col("page_id").cast("string"), F.lit(NO_ID))
    head = F.concat(
        F.lit(f"WARC/1.1{CRLF}"),
        field("WARC-Type", F.when(again, "revisit").otherwise("response")),
        field("WARC-Record-ID", F.concat(F.lit(f"<{ID}"), page, F.lit(">"))),
        field("WARC-Date", F.date_format(F.to_utc_timestamp(F.timestamp_seconds(F.lit(1_700_000_000) + F.pmod(F.coalesce("page_id", F.lit(0)), F.lit(1_000_000_000))), F.current_timezone()), "yyyy-MM-dd'T'HH:mm:ss'Z'")),
        field("WARC-Target-URI", url),
        field("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))),
        field("WARC-Profile", F.when(again, "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
        field("WARC-Refers-To", F.when(again, F.concat(F.lit(f"<{ID}"), F.col("last").cast("string"), F.lit(">")))),
        field("Content-Type", F.lit("application/http; msgtype=response")),
        field("Content-Length", F.octet_length(block).cast("string")),
        F.lit(CRLF),
    )
    return full.select(F.concat(head, block).alias("value"))


def write_archives(pages: DataFrame, path: str, least: int = 1000) -> None:
    records(pages, least).write.option("lineSep", CRLF + CRLF).option("compression", "gzip").option("maxRecordsPerFile", RECORDS).text(path)


def url_key(url: str | None) -> str:
    """Host labels in reverse, then path and query: captures of a site stand together."""
    if not url:
        return ""
    try:
        at = urlsplit(url)
        host = at.hostname or ""
    except ValueError:
        return url
    return ",".join(reversed(host.split("."))) + ")" + (at.path or "/").lower() + (f"?{at.query.lower()}" if at.query else "")


def parse(raw: bytes):
    """(header fields, HTTP header fields, payload) of the records of an archive."""
    at = 0
    while at < len(raw):
        cut = raw.index(b"\r\n\r\n", at)
        fields = _fields(raw[at:cut])
        size = int(fields["content-length"])
        block = raw[cut + 4 : cut + 4 + size]
        head, _, payload = block.partition(b"\r\n\r\n")
        yield fields, _fields(head), payload
        at = cut + 4 + size + 4


def _fields(head: bytes) -> dict[str, str]:
    return {k.decode().lower(): v.decode() for k, _, v in (x.partition(b": ") for x in head.split(b"\r\n")[1:])}


def in_order(row):
    """By URL key and time, then by page; a page without an id comes first."""
    return row[0], row[1], row[2] is not None, row[2] or 0


def read_runs(spark, path: str) -> DataFrame:
    """Index entries of the archives in a folder; those of a file are a run, sorted by URL key and time."""

    def number(name: str | None) -> int | None:
        name = NO_ID if name is None else name.strip("<>").removeprefix(ID)
        return None if name == NO_ID else int(name)

    def run(batches):
        for b in batches:
            for name, content in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                rows = []
                for fields, http, payload in parse(gzip.decompress(content.as_py())):
                    digest, size = fields["warc-payload-digest"].removeprefix("sha1:"), int(http["content-length"])
                    if fields["warc-type"] == "response":
                        digest, size = hashlib.sha1(payload).hexdigest(), len(payload)
                    rows.append((url_key(fields.get("warc-target-uri")), fields["warc-date"], number(fields["warc-record-id"]), fields["warc-type"], number(fields.get("warc-refers-to")), size, digest))
                rows.sort(key=in_order)
                if rows:
                    kinds = (pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string())
                    arrays = [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)]
                    yield pa.RecordBatch.from_arrays([*arrays, pa.array([name] * len(rows)), pa.array(range(len(rows)), pa.int64())], [x.split()[0] for x in INDEX.split(", ")])

    return spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").load(path).select("path", "content").mapInArrow(lean(run), INDEX)


class LoserTree:
    """Merges k sorted runs: each step replays one path, against the losers kept on it."""

    def __init__(self, runs, key):
        self.runs, self.key = [iter(r) for r in runs], key
        self.k = max(1, len(self.runs))
        self.heads = [self._next(i) for i in range(len(self.runs))] or [None]
        self.losers = [-1] * self.k
        for i in range(self.k):
            self._replay(i)

    def _next(self, i: int):
        row = next(self.runs[i], None)
        return None if row is None else (self.key(row), i, row)

    def _beats(self, a: int, b: int) -> bool:
        x, y = self.heads[a], self.heads[b]
        return x is not None and (y is None or x[:2] < y[:2])

    def _replay(self, i: int) -> None:
        at = (i + self.k) // 2
        while at:
            other = self.losers[at]
            if other < 0:  # the first to come here waits for its opponent
                self.losers[at] = i
                return
            if self._beats(other, i):
                self.losers[at], i = i, other
            at //= 2
        self.losers[0] = i

    def __iter__(self):
        while (head := self.heads[self.losers[0]]) is not None:
            i = self.losers[0]
            yield head[2]
            self.heads[i] = self._next(i)
            self._replay(i)


class RunFile:
    """Sorted runs on a task's scratch disk, as blocks of few rows; of each run one block is in memory at a time."""

    def __init__(self, schema: pa.Schema):
        self.schema, self.file = schema, tempfile.TemporaryFile()
        self.runs: list[list[tuple[int, int]]] = []

    def add(self, batch: pa.RecordBatch) -> None:
        """Appends rows to the last run."""
        for i in range(0, batch.num_rows, BLOCK):
            data = batch.slice(i, BLOCK).serialize()
            self.file.seek(0, 2)
            self.runs[-1].append((self.file.tell(), data.size))
            self.file.write(data)

    def rows(self, run: list[tuple[int, int]]):
        for at, size in run:
            self.file.seek(at)
            batch = pa.ipc.read_record_batch(pa.py_buffer(self.file.read(size)), self.schema)
            yield from zip(*(c.to_pylist() for c in batch.columns), strict=True)

    def merged(self):
        """Batches of all runs in order; more than FAN runs are merged in several passes."""
        waiting = self.runs
        while len(waiting) > FAN:
            self.runs = []
            for i in range(0, len(waiting), FAN):
                self.runs.append([])
                for batch in self._merge(waiting[i : i + FAN]):
                    self.add(batch)
            waiting = self.runs
        yield from self._merge(waiting)

    def _merge(self, runs):
        held = []
        for row in LoserTree([self.rows(r) for r in runs], in_order):
            held.append(row)
            if len(held) == 4096:
                yield self._batch(held)
                held = []
        if held:
            yield self._batch(held)

    def _batch(self, rows) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), self.schema, strict=True)], schema=self.schema)


def merged(runs: DataFrame) -> DataFrame:
    """All runs as one, in the order of URL key, time and page: ranges of it, each merged from disk by a loser tree."""

    def run(batches):
        file, last = None, None
        for b in batches:
            if not b.num_rows:
                continue
            file = file or RunFile(b.schema)
            names = b.column(7).to_pylist()
            cuts = [0, *(i for i in range(1, len(names)) if names[i] != names[i - 1]), len(names)]
            for s, e in zip(cuts[:-1], cuts[1:], strict=True):
                if names[s] != last:
                    file.runs.append([])
                    last = names[s]
                file.add(b.slice(s, e - s))
        if file is not None:
            yield from file.merged()

    dealt = runs.repartitionByRange(partitions(runs.sparkSession), "urlkey", "captured", "page_id")
    return dealt.sortWithinPartitions("run", "place").mapInArrow(lean(run), INDEX)


def archive(pages: DataFrame, path: str | None = None, least: int = 1000) -> DataFrame:
    """Write the pages' archives, read them back, and return their index in order."""
    spark = pages.sparkSession
    path = path or f"{shared_folder(spark).rstrip('/')}/tempcorr-warc-{uuid.uuid4().hex}"
    write_archives(pages, path, least)
    return merged(written(read_runs(spark, path), "op5-runs"))
