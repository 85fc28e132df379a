"""Anchored runs: cut every text into runs of windows that share their smallest k-gram, so that equal windows meet.

A *unit* is a byte or a word; a *window* is `window` consecutive units of one text. Each window has an anchor, the
smallest hash among its k-grams, which depends on the window's content alone: equal windows have equal anchors. A *run*
is a maximal stretch of consecutive windows with one anchor value. Where a long passage is repeated, whole runs are
repeated, so a table of runs (one row for every few units) finds nearly all of it; only the runs at a passage's ends
have to be looked at window by window ("open" runs). Hot anchors are found first and dealt by anchor and run.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr.llm.common import lean, mix, packed, partitions, text_bytes, unpacked, written

BASE, INVERSE = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 1 << 64)
#: Longer runs (periodic text) are split; no window is lost.
MOST_WINDOWS = 4096
#: Units that are hashed at once.
BLOCK = 1 << 18
BYTE_HASHES = np.array([xxhash.xxh3_64_intdigest(bytes([x]), 7) for x in range(256)], np.uint64)
IS_WORD = np.array([x not in b" \t\n\v\f\r" for x in range(256)], np.int8)
RUNS = "anchor long, run long, doc_id long, start int, windows int, tied boolean"
FOUND = "open boolean, anchor long, doc_id long, start int, windows int, low long, settled boolean"
STRINGS = "anchor long, doc_id long, start int, windows int, low long, settled boolean, content binary"
SPANS = "doc_id long, start int, end int"


class Words:
    """Words as units: where each begins and ends; content is words joined by one space."""

    def units(self, text: bytes):
        return WordPlaces(text)

    def hashes(self, units) -> np.ndarray:
        return word_hashes(units)

    @staticmethod
    def part(units, start: int, end: int) -> bytes:
        return units.words(start, end)


class WordPlaces:
    """The words of a text or of a part of it, as places in its bytes."""

    def __init__(self, text: bytes, starts: np.ndarray | None = None, ends: np.ndarray | None = None):
        self.text = text
        if starts is None:
            edge = np.diff(IS_WORD[np.frombuffer(text, np.uint8)], prepend=np.int8(0), append=np.int8(0))
            starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        self.at, self.to = starts, ends

    def __len__(self) -> int:
        return len(self.at)

    def __getitem__(self, s: slice) -> WordPlaces:
        if s.start == 0 and s.stop >= len(self.at):
            return self
        return WordPlaces(self.text, self.at[s], self.to[s])

    @property
    def raw(self) -> np.ndarray:
        low = self.at[0] if len(self.at) else 0
        return np.frombuffer(self.text, np.uint8)[low : self.to[-1] if len(self.to) else 0]

    @property
    def starts(self) -> np.ndarray:
        return self.at - self.at[:1]

    @property
    def ends(self) -> np.ndarray:
        return self.to - self.at[:1]

    def words(self, start: int, end: int) -> bytes:
        return b" ".join(self.text[self.at[start] : self.to[end - 1]].split()) if end > start else b""


def word_hashes(places: WordPlaces, most: int = 1 << 20) -> np.ndarray:
    """A 64-bit hash of each word, by blocks of about `most` bytes."""
    n, out, s = len(places), [np.zeros(0, np.uint64)], 0
    while s < n:
        e = max(s + 1, int(np.searchsorted(places.to, places.at[s] + most, side="right")))
        part = places[s:e]
        out.append(Rolling(BYTE_HASHES[part.raw]).at(part.starts, part.ends))
        s = e
    return out[1] if len(out) == 2 else np.concatenate(out)


class Bytes:
    """Bytes as units."""

    def units(self, text: bytes):
        return text

    def hashes(self, units) -> np.ndarray:
        return BYTE_HASHES[np.frombuffer(units, np.uint8)]

    @staticmethod
    def part(units, start: int, end: int) -> bytes:
        return units[start:end]


class Rolling:
    """Hashes of any substring of a unit-hash array, from prefix sums modulo 2**64."""

    #: Powers that a worker keeps: enough for a block of units, but never for a text of any length.
    KEPT = 1 << 21
    up = down = np.ones(1, np.uint64)

    def __init__(self, h: np.ndarray):
        n = len(h)
        if len(Rolling.up) <= n <= Rolling.KEPT:
            Rolling.up, Rolling.down = (self._powers(base, min(2 * n, Rolling.KEPT) + 1) for base in (BASE, INVERSE))
        up, self.down = (Rolling.up, Rolling.down) if len(Rolling.up) > n else (self._powers(base, n + 1) for base in (BASE, INVERSE))
        self.sums = np.zeros(n + 1, np.uint64)
        np.cumsum(h * up[:n], out=self.sums[1:])

    @staticmethod
    def _powers(base: int, n: int) -> np.ndarray:
        p = np.full(n, base, np.uint64)
        p[0] = 1
        return np.multiply.accumulate(p)

    def all(self, size: int) -> np.ndarray:
        n = len(self.sums) - size
        return mix((self.sums[size:] - self.sums[:n]) * self.down[:n])

    def at(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return mix((self.sums[ends] - self.sums[starts]) * self.down[starts]) ^ mix((ends - starts).astype(np.uint64))


def sliding_min(x: np.ndarray, size: int) -> np.ndarray:
    """The smallest of x[i], ..., x[i + size - 1], by doubling."""
    have = 1
    while have < size:
        step = min(have, size - have)
        x = np.minimum(x[:-step], x[step:])
        have += step
    return x


def ties(grams: np.ndarray, anchor: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Which runs have their smallest k-gram at two places, as runs have that hold a window twice."""
    at = np.flatnonzero(grams <= anchor.max())
    _, rank = np.unique(np.concatenate([anchor, grams[at]]), return_inverse=True)
    n = len(grams) + 1
    places = np.sort(rank[len(anchor) :] * n + at)
    own = rank[: len(anchor)] * n
    return np.searchsorted(places, own + end) - np.searchsorted(places, own + start) > 1


def runs_of(h: np.ndarray, lengths: np.ndarray, window: int, k: int, tied: bool):
    """Of several texts put together: text index, start in it, windows, anchor, hash of the run's content, is it tied."""
    ends = np.cumsum(lengths)
    if len(h) < window:
        return None
    valid = np.ones(len(h) - window + 1, bool)
    for e, n in zip(ends.tolist(), lengths.tolist(), strict=True):
        valid[max(e - n, e - window + 1) : e] = False
    at = np.flatnonzero(valid)
    if not len(at):
        return None
    roll = Rolling(h)
    grams = roll.all(k)
    v = sliding_min(grams, window - k + 1)[at]
    first = np.flatnonzero(np.r_[True, (v[1:] != v[:-1]) | (at[1:] != at[:-1] + 1)])
    count = np.diff(np.r_[first, len(at)])
    start, anchor = at[first], v[first]
    if count.max() > MOST_WINDOWS:
        pieces = -(-count // MOST_WINDOWS)
        j = np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        start, anchor, count = np.repeat(start, pieces) + j * MOST_WINDOWS, np.repeat(anchor, pieces), np.minimum(MOST_WINDOWS, np.repeat(count, pieces) - j * MOST_WINDOWS)
    text = np.searchsorted(ends, start, side="right")
    two = ties(grams, anchor, start, start + count + window - k) if tied else np.zeros(len(start), bool)
    return text, start - (ends - lengths)[text], count, anchor.view(np.int64), roll.at(start, start + count + window - 1).view(np.int64), two


def hashed(batches: Iterator[pa.RecordBatch], kind, window: int, k: int, tied: bool = False):
    """Runs of all texts of the batches: doc ids, starts, windows, anchors, run hashes, ties; long texts block by block."""
    ids, parts, sizes, shift, total = [], [], [], [], 0

    def out():
        got = runs_of(np.concatenate(parts), np.array(sizes), window, k, tied)
        if got is not None:
            text, start, count, anchor, run, two = got
            yield np.array(ids)[text], start + np.array(shift)[text], count, anchor, run, two

    for batch in batches:
        for doc, text in zip(batch.column(0).to_pylist(), text_bytes(batch.column(1)), strict=True):
            if text is None:
                continue
            units = kind.units(text)
            for b in range(0, len(units) - window + 1, BLOCK):
                h = kind.hashes(units[b : b + BLOCK + window - 1])
                ids.append(doc), parts.append(h), sizes.append(len(h)), shift.append(b)
                total += len(h)
                if total >= BLOCK:
                    yield from out()
                    ids, parts, sizes, shift, total = [], [], [], [], 0
    if parts:
        yield from out()


def table_of(docs: DataFrame, make, window: int, k: int, tied: bool = False) -> DataFrame:
    def run(batches):
        for doc, start, count, anchor, r, two in hashed(batches, make(), window, k, tied):
            yield pa.RecordBatch.from_arrays([pa.array(anchor), pa.array(r), pa.array(doc), pa.array(start.astype(np.int32)), pa.array(count.astype(np.int32)), pa.array(two)], ["anchor", "run", "doc_id", "start", "windows", "tied"])

    return docs.select("doc_id", "text").mapInArrow(lean(run), RUNS)


def hot_anchors(docs: DataFrame, make, window: int, k: int, most: int) -> DataFrame:
    """Anchors with more than `most` runs, of those that a part of the input has 32 times in some millions of runs.

    One that is spread thinner stays with the others: it is settled alike, but by one task.
    """

    def run(batches):
        held: list[np.ndarray] = []
        size = 0

        def out(least):
            a, n = np.unique(np.concatenate(held), return_counts=True)
            keep = n >= least
            return pa.RecordBatch.from_arrays([pa.array(a[keep]), pa.array(n[keep])], ["anchor", "n"])

        for _, _, _, anchor, _, _ in hashed(batches, make(), window, k):
            held.append(anchor)
            size += len(anchor)
            if size >= 1 << 21:
                yield out(32)
                held, size = [], 0
        if held:
            yield out(32)

    return docs.select("doc_id", "text").mapInArrow(lean(run), "anchor long, n long").groupBy("anchor").agg(F.sum("n").alias("n")).where(F.col("n") > most).select("anchor")


def settle(runs: DataFrame, hot: DataFrame | None, ordered: bool) -> DataFrame:
    """Rows of FOUND: runs that are settled as repeats, and open runs with one row for each distinct content.

    ordered: a repeat is what also starts in a document with a smaller id; else what starts anywhere else too. The rows
    of an anchor come to one task, sorted, and are taken in pieces that end where an anchor ends. The rows of a hot
    anchor are dealt by their run too; what of them is not settled stays open.
    """
    n = partitions(runs.sparkSession)
    if hot is None:
        runs = runs.withColumn("salt", F.lit(0))
    else:
        runs = runs.join(F.broadcast(hot.withColumn("hot", F.lit(1))), "anchor", "left").withColumn("salt", F.when(F.col("hot").isNull(), 0).otherwise(1 + F.pmod(F.xxhash64("run"), F.lit(n))).cast("int")).drop("hot")
    dealt = runs.select("anchor", "salt", "run", "doc_id", "start", "windows", "tied").repartition(n, "anchor", "salt").sortWithinPartitions("anchor", "salt")

    def one(cols):
        anchor, salt, run, doc, start, windows, tied = cols
        order = np.lexsort((start, doc, run, salt, anchor))
        anchor, salt, run, doc, start, windows, tied = (c[order] for c in cols)
        new_group = np.r_[True, (anchor[1:] != anchor[:-1]) | (salt[1:] != salt[:-1])]
        new_run = new_group | np.r_[True, run[1:] != run[:-1]]
        run_no = np.cumsum(new_run) - 1
        copies = np.bincount(run_no)[run_no]
        group_no = np.cumsum(new_group) - 1
        contested = (np.bincount(group_no, new_run)[group_no] > 1) | (salt > 0) | tied
        low = doc[np.flatnonzero(new_run)][run_no]
        settled = doc > low if ordered else copies > 1
        opened = contested & (new_run | ((doc == low) if ordered else False))
        for is_open, keep in ((False, settled), (True, opened)):
            if keep.any():
                yield pa.RecordBatch.from_arrays([pa.array(np.full(keep.sum(), is_open)), *(pa.array(c[keep]) for c in (anchor, doc, start, windows, low, settled))], ["open", "anchor", "doc_id", "start", "windows", "low", "settled"])

    def run(batches):
        held: list[list[np.ndarray]] = []
        size = 0
        for batch in batches:
            cols = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            if not len(cols[0]):
                continue
            last = np.flatnonzero((cols[0] != cols[0][-1]) | (cols[1] != cols[1][-1]))
            cut = last[-1] + 1 if len(last) else 0
            if cut and size + cut >= 1 << 17:
                yield from one([np.concatenate(x) for x in zip(*held, [c[:cut] for c in cols], strict=True)] if held else [c[:cut] for c in cols])
                held, size, cols = [], 0, [c[cut:] for c in cols]
            held.append(cols)
            size += len(cols[0])
        if held:
            yield from one([np.concatenate(x) for x in zip(*held, strict=True)])

    return dealt.mapInArrow(lean(run), FOUND)


def zipped(docs: DataFrame) -> DataFrame:
    """(doc_id, packed): texts compressed before they are shuffled."""

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([None if t is None else packed(t) for t in text_bytes(b.column(1))], pa.binary())], ["doc_id", "packed"])

    return docs.select("doc_id", "text").mapInArrow(lean(run), "doc_id long, packed binary")


def strings(docs: DataFrame, opened: DataFrame, make, window: int) -> DataFrame:
    """Rows of STRINGS: the content of open runs, fetched from their documents."""
    places = opened.groupBy("doc_id").agg(F.collect_list(F.struct("start", "windows", "anchor", "low", "settled")).alias("places"))

    def run(batches):
        kind = make()
        for b in batches:
            rows, size = [], 0
            for doc, text, places in zip(*(c.to_pylist() for c in b.columns), strict=True):
                units = kind.units(unpacked(text))
                for p in places:
                    if p["start"] + p["windows"] + window - 1 > len(units):
                        continue  # another row with this doc_id
                    content = kind.part(units, p["start"], p["start"] + p["windows"] + window - 1)
                    rows.append((p["anchor"], doc, p["start"], p["windows"], p["low"], p["settled"], content))
                    size += len(content)
                if size > 4_000_000:
                    yield out(rows)
                    rows, size = [], 0
            if rows:
                yield out(rows)

    def out(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.bool_(), pa.binary()), strict=True)], ["anchor", "doc_id", "start", "windows", "low", "settled", "content"])

    return zipped(docs).join(places, "doc_id").mapInArrow(lean(run), STRINGS)


def pieces(batches: Iterator[pa.RecordBatch], most: int):
    """Rows of STRINGS, sorted by anchor, as lists of at least `most` bytes of content that end where an anchor ends."""
    held, size = [], 0
    for b in batches:
        for row in b.to_pylist():
            if size >= most and row["anchor"] != held[-1]["anchor"]:
                yield held
                held, size = [], 0
            held.append(row)
            size += len(row["content"])
    if held:
        yield held


def window_hashes(found: DataFrame, make, window: int) -> DataFrame:
    """A row for every window of the given strings: for hot anchors, whose strings must not meet in one task."""

    def run(batches):
        kind = make()
        for b in batches:
            cols = [[], [], [], [], [], []]
            for row in b.to_pylist():
                h = Rolling(kind.hashes(kind.units(row["content"]))).all(window).view(np.int64)
                for c, v in zip(cols, (np.full(len(h), row["anchor"]), h, np.full(len(h), row["doc_id"]), row["start"] + np.arange(len(h), dtype=np.int32), np.full(len(h), row["low"]), np.full(len(h), row["settled"])), strict=True):
                    c.append(v)
            if cols[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in cols], ["anchor", "h", "doc_id", "at", "low", "settled"])

    return found.mapInArrow(lean(run), "anchor long, h long, doc_id long, at int, low long, settled boolean")


def repeats(docs: DataFrame, make, window: int, k: int, ordered: bool, resolve, name: str) -> DataFrame:
    """Spans, in units, of all repeated windows. resolve(rows) yields (doc_id, start, windows) for a piece of open strings."""
    spark = docs.sparkSession
    n = partitions(spark)
    runs = table_of(docs, make, window, k, not ordered)
    total = docs.select((F.sum(F.octet_length("text")) / (F.lit(33) if window < 50 else F.lit(180))).alias("n")).first()["n"] or 0
    hot = written(hot_anchors(docs, make, window, k, int(total / n / 4) + 2000), f"{name}-hot")
    found = written(settle(runs, hot, ordered), f"{name}-runs")
    done = found.where("not open and settled").select("doc_id", "start", (F.col("start") + F.col("windows") + (window - 1)).cast("int").alias("end"))
    texts = strings(docs, found.where("open"), make, window)
    hot_side = F.broadcast(hot)  # at most eight anchors for each partition of the shuffle, by the threshold above
    flagged = written(texts.join(hot_side.withColumn("hot", F.lit(True)), "anchor", "left"), f"{name}-open")

    def piecewise(batches):
        for rows in pieces(batches, 1_500_000):
            out = list(resolve(rows))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int64(), pa.int32(), pa.int32()), strict=True)], ["doc_id", "start", "end"])

    columns = [x.split()[0] for x in STRINGS.split(", ")]
    usual = flagged.where("hot is null").select(*columns).repartition(n, "anchor").sortWithinPartitions("anchor", "doc_id", "start").mapInArrow(lean(piecewise), SPANS)
    rest = window_hashes(flagged.where("hot").select(*columns), make, window)
    least = rest.groupBy("anchor", "h").agg(F.min("low").alias("least"), F.count("*").alias("times"))
    rest = rest.where("not settled" if not ordered else "true").join(least, ["anchor", "h"]).where("least < doc_id" if ordered else "times > 1").select("doc_id", F.col("at").alias("start"), (F.col("at") + window).cast("int").alias("end"))
    return done.unionByName(usual).unionByName(rest)


def with_spans(docs: DataFrame, spans: DataFrame, f, schema: str) -> DataFrame:
    """Every document with the spans found in it, for a mapInArrow function over (doc_id, packed text, starts, ends)."""
    per = spans.groupBy("doc_id").agg(F.collect_list(F.struct("start", "end")).alias("spans"))
    return zipped(docs).join(per, "doc_id", "left").mapInArrow(lean(f), schema)


def covered(n: int, spans) -> np.ndarray:
    """Which of n units the spans cover."""
    edge = np.zeros(n + 1, np.int32)
    if spans:
        s = np.array([x["start"] for x in spans])
        e = np.array([x["end"] for x in spans])
        np.add.at(edge, s, 1)
        np.add.at(edge, np.minimum(e, n), -1)
    return np.cumsum(edge[:n]) > 0
