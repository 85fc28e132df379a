"""Benchmark decontamination: a prefix-filtered set join between windows of items and documents.

An item's windows are sets of shingles, each with its place. Shingles are ordered by how often the documents have them,
rarest first; to hold a window whole, a document must hold the first shingle of that order, so that a prefix of one
shingle is joined. The shingle's place in the window and the lengths of both bound where the window can begin; each such
place is compared word by word.

The items are broadcast, in blocks of a checked size: more items mean more blocks, each over all documents.

Defined results: null or empty text has no words: such a document is clean, such an item has no window; repeated rows of
an item count once in n_items; repeated rows of a document are judged each, and rows of one doc_id with other texts each
by its own text, whatever the number of blocks; an empty benchmark leaves all documents clean; other columns are ignored,
whatever their names. A very long text takes some 100 bytes of memory for each word.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr.llm.common import keyed, lean, mix, text_bytes

#: Everything but ASCII letters, digits and bytes of other characters separates words; upper case is lowered.
FOLD = bytes(x + 32 if 65 <= x <= 90 else x if 48 <= x <= 57 or 97 <= x <= 122 or x >= 128 else 32 for x in range(256))
SHINGLE = 4
#: Bytes of items that are broadcast at once.
MOST_BYTES = 64 << 20
HITS = "doc_id long, text_key long, n_words long, spans array<struct<start:int,end:int>>, items array<string>"
OUT = "doc_id long, text_key long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


def words_of(text: bytes | None) -> list[bytes]:
    """The words of a contract's text."""
    return text.translate(FOLD).split() if text else []


class Windows:
    """All distinct windows of items, with the items that have them."""

    def __init__(self, items: list[tuple[str, bytes | None]], size: int):
        self.vocabulary: dict[bytes, int] = {}
        owners: dict[tuple[int, ...], set[str]] = {}
        for item, text in items:
            codes = [self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words_of(text)]
            for i in range(max(1, len(codes) - size + 1) if codes else 0):
                owners.setdefault(tuple(codes[i : i + size]), set()).add(item)
        self.windows = [np.array(w, np.int32) for w in owners]
        self.owners = [sorted(o) for o in owners.values()]
        self.lengths = sorted({min(SHINGLE, len(w)) for w in self.windows})
        #: For each shingle length: the sorted hashes of all shingles of windows.
        self.shingles = {k: np.unique(np.concatenate([shingle_hashes(w, k) for w in self.windows if min(SHINGLE, len(w)) == k])) for k in self.lengths}

    def codes(self, words: list[bytes]) -> np.ndarray:
        get = self.vocabulary.get
        return np.fromiter([get(w, -1) for w in words], np.int32, len(words))

    def order(self, counts: dict[tuple[int, int], int]) -> None:
        """Index every window by its rarest shingle."""
        self.keys: dict[int, np.ndarray] = {}
        self.at: dict[int, dict[int, list[tuple[int, int]]]] = {}
        index: dict[int, dict[int, list[tuple[int, int]]]] = {k: {} for k in self.lengths}
        for i, w in enumerate(self.windows):
            k = min(SHINGLE, len(w))
            h = shingle_hashes(w, k)
            where = min(range(len(h)), key=lambda j: (counts.get((k, int(h[j])), 0), int(h[j]), j))
            index[k].setdefault(int(h[where]), []).append((i, where))
        for k in self.lengths:
            self.keys[k] = np.array(sorted(index[k]), np.int64)
            self.at[k] = index[k]

    def hits(self, codes: np.ndarray):
        """(start, window) of all occurrences."""
        for k in self.lengths:
            where, found = matches(codes, k, self.keys[k])
            if not len(where):
                continue
            for h in np.unique(found).tolist():
                places = where[found == h]
                for i, shift in self.at[k][h]:
                    w = self.windows[i]
                    starts = places - shift
                    starts = starts[(starts >= 0) & (starts <= len(codes) - len(w))]
                    for j in range(len(w)):
                        starts = starts[codes[starts + j] == w[j]]
                        if not len(starts):
                            break
                    if len(starts):
                        yield starts, i


def shingle_hashes(codes: np.ndarray, k: int) -> np.ndarray:
    n = len(codes) - k + 1
    h = np.zeros(n, np.uint64)
    for j in range(k):
        h = mix(h + codes[j : j + n].astype(np.uint64) + np.uint64(1))
    return h.view(np.int64)


def matches(codes: np.ndarray, k: int, keys: np.ndarray):
    """Places whose k words are all known and whose shingle is among the sorted keys, and the shingles."""
    n = len(codes) - k + 1
    if n <= 0 or not len(keys):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    known = np.cumsum(np.r_[0, codes >= 0])
    where = np.flatnonzero(known[k:] - known[:-k] == k)
    if not len(where):
        return where, np.zeros(0, np.int64)
    h = np.zeros(len(where), np.uint64)
    for j in range(k):
        h = mix(h + codes[where + j].astype(np.uint64) + np.uint64(1))
    h = h.view(np.int64)
    same = keys[np.minimum(np.searchsorted(keys, h), len(keys) - 1)] == h
    return where[same], h[same]


def _rarity(docs: DataFrame, windows: Windows) -> dict[tuple[int, int], int]:
    """How often the documents have each shingle of the windows; at most as many rows as the items have shingles."""

    def run(batches):
        counts = {k: np.zeros(len(s), np.int64) for k, s in windows.shingles.items()}
        for b in batches:
            for text in text_bytes(b.column(1)):
                codes = windows.codes(words_of(text))
                for k, s in windows.shingles.items():
                    _, h = matches(codes, k, s)
                    np.add.at(counts[k], np.searchsorted(s, h), 1)
        for k, c in counts.items():
            some = c > 0
            yield pa.RecordBatch.from_arrays([pa.array(np.full(some.sum(), k, np.int32)), pa.array(windows.shingles[k][some]), pa.array(c[some])], ["k", "h", "n"])

    found = docs.mapInArrow(lean(run), "k int, h long, n long").groupBy("k", "h").agg(F.sum("n").alias("n")).collect()
    return {(r["k"], r["h"]): r["n"] for r in found}


def _hits(docs: DataFrame, items: list[tuple[str, bytes | None]], size: int) -> DataFrame:
    windows = Windows(items, size)
    windows.order(_rarity(docs, windows) if windows.windows else {})

    def run(batches):
        for b in batches:
            rows = []
            for doc, text, key in zip(b.column(0).to_pylist(), text_bytes(b.column(1)), b.column(2).to_pylist(), strict=True):
                words = words_of(text)
                edge, found = np.zeros(len(words) + 1, np.int64), set()
                for starts, i in windows.hits(windows.codes(words)):
                    np.add.at(edge, starts, 1)
                    np.add.at(edge, starts + len(windows.windows[i]), -1)
                    found.update(windows.owners[i])
                turns = np.diff((np.cumsum(edge) > 0).astype(np.int8), prepend=np.int8(0)) if found else edge[:0]
                rows.append((doc, key, len(words), [{"start": s, "end": e} for s, e in zip(np.flatnonzero(turns == 1).tolist(), np.flatnonzero(turns == -1).tolist(), strict=True)], sorted(found)))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])), pa.list_(pa.string())), strict=True)], ["doc_id", "text_key", "n_words", "spans", "items"])

    return docs.select("doc_id", "text", F.xxhash64("text").alias("text_key")).mapInArrow(lean(run), HITS)


def clean(docs: DataFrame, benchmark: DataFrame, size: int = 13, share: int = 20) -> DataFrame:
    """The documents that are not contaminated, with all their columns."""
    bad = judge(find(docs, benchmark, size), share).where("contaminated").select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key")).distinct()
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("_id")) & (F.xxhash64(F.col("text").cast("string")) == F.col("_key"))
    return docs.join(bad, same, "left_anti").select(*docs.columns)


def find(docs: DataFrame, benchmark: DataFrame, size: int = 13, most_bytes: int = MOST_BYTES) -> DataFrame:
    """Rows of HITS: the words of every document inside any window of an item, and the items found."""
    docs = keyed(docs)
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text"))
    total = items.agg(F.sum(F.octet_length("text")).alias("n")).first()["n"] or 0
    blocks = -(-total // most_bytes) or 1
    parts = []
    for i in range(blocks):
        part = items.where(F.pmod(F.xxhash64("text"), F.lit(blocks)) == i)
        parts.append(_hits(docs, [(r["item_id"], None if r["text"] is None else r["text"].encode()) for r in part.collect()], size))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    if blocks > 1:  # equal rows have equal results: as many of them as there were
        out = out.groupBy("doc_id", "text_key").agg(F.max("n_words").alias("n_words"), F.flatten(F.collect_list("spans")).alias("spans"), F.array_distinct(F.flatten(F.collect_list("items"))).alias("items"), F.explode(F.array_repeat(F.lit(0), (F.count("*") / blocks).cast("int"))).alias("_copy")).drop("_copy")
    return out


def judge(hits: DataFrame, share: int = 20) -> DataFrame:
    """Rows of OUT. A document is contaminated when at least one in `share` of its words is hit."""

    def run(batches):
        for b in batches:
            rows = []
            for doc, key, n, spans, items in zip(*(c.to_pylist() for c in b.columns), strict=True):
                edge = np.zeros(n + 1, np.int64)
                for s in spans:
                    edge[s["start"]] += 1
                    edge[s["end"]] -= 1
                hit = int((np.cumsum(edge) > 0).sum()) if spans else 0
                rows.append((doc, key, n, hit, len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), hit > 0 and share * hit >= n))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_()), strict=True)], ["doc_id", "text_key", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"])

    return hits.select("doc_id", "text_key", "n_words", "spans", "items").mapInArrow(lean(run), OUT)
