"""Suffix-array dedup: bytes covered by a long string that also starts anywhere else are removed.

Texts are cut into anchored runs (see anchors.py), so that equal strings meet in one shard and text that cannot repeat is
never sorted. A shard's strings are sorted by external induction (induced.py): neighbours in the order that agree in
`window` bytes are repeats. Whole runs that repeat are settled by their hash; the strings of hot anchors, which must not
meet in one task, are matched window by window.

Defined results: null or empty text has 0 bytes, nothing removed and the hash of no bytes; texts shorter than the window
lose nothing; every row is a place of its own, also where rows share a doc_id; an empty table gives no rows; other columns
are ignored, whatever their names. A very long text is hashed in blocks and cut as a whole, in some 20 bytes of memory
for each of its bytes.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr.llm import anchors
from tempcorr.llm.common import keyed, lean, packed, text_bytes, unpacked, written
from tempcorr.llm.induced import suffix_array

SCHEMA = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"


def repeated(window: int):
    """Resolves a piece of open strings: the windows that come twice in it."""

    def alike(rows):
        """Without the strings whose anchor has no window hash twice."""
        i = 0
        while i < len(rows):
            j = i
            while j < len(rows) and rows[j]["anchor"] == rows[i]["anchor"]:
                j += 1
            group, i = rows[i:j], j
            hashes = [anchors.Rolling(anchors.BYTE_HASHES[np.frombuffer(r["content"], np.uint8)]).all(window) for r in group]
            _, at, times = np.unique(np.concatenate(hashes), return_inverse=True, return_counts=True)
            often = np.split(times[at] > 1, np.cumsum([len(h) for h in hashes])[:-1])
            yield from (r for r, o in zip(group, often, strict=True) if o.any())

    def resolve(rows):
        rows = list(alike(rows))
        if not rows:
            return
        text = b"".join(r["content"] for r in rows)
        sizes = np.array([len(r["content"]) for r in rows])
        ends = np.cumsum(sizes + 1)  # a separator, larger than all bytes, after each
        t = np.full(ends[-1], 256, np.int32)
        t[np.delete(np.arange(ends[-1]), ends - 1)] = np.frombuffer(text, np.uint8)
        order = suffix_array(t, 257)
        order = order[order < len(t)]
        left = ends[np.searchsorted(ends, order, side="right")] - 1 - order  # bytes to the end of the own string
        order = order[left >= window]
        h = anchors.Rolling(np.r_[anchors.BYTE_HASHES, np.uint64(1)][t]).all(window)[order]
        same = h[1:] == h[:-1]
        twice = np.zeros(len(t) + 1, np.int8)
        twice[order[1:][same]] = 1
        twice[order[:-1][same]] = 1
        edge = np.diff(twice, prepend=np.int8(0))
        for s, e in zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True):
            i = int(np.searchsorted(ends, s, side="right"))
            if not rows[i]["settled"]:
                at = rows[i]["start"] + s - int(ends[i] - sizes[i] - 1)
                yield rows[i]["doc_id"], at, at + (e - s) + window - 1

    return resolve


def numbered(docs: DataFrame) -> DataFrame:
    """(row, doc_id, packed): every row of the input under a number of its own, its text compressed; a written table."""

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([None if t is None else packed(t) for t in text_bytes(b.column(2))], pa.binary())], ["row", "doc_id", "packed"])

    rows = keyed(docs).select(F.monotonically_increasing_id().alias("row"), "doc_id", "text")
    return written(rows.mapInArrow(lean(run), "row long, doc_id long, packed binary"), "op3-rows")


def plain(rows: DataFrame) -> DataFrame:
    """(doc_id, text) as the anchors' functions take them: the number of the row, and its bytes."""

    def run(batches):
        for b in batches:
            for p in (b.slice(i, 64) for i in range(0, b.num_rows, 64)):
                yield pa.RecordBatch.from_arrays([p.column(0), pa.array([None if t is None else unpacked(t) for t in p.column(1).to_pylist()], pa.binary())], ["doc_id", "text"])

    return rows.select("row", "packed").mapInArrow(lean(run), "doc_id long, text binary")


def strings(rows: DataFrame, window: int = 400) -> DataFrame:
    """(doc_id, start, end): spans of bytes that are repeated, by the number of the row."""
    return anchors.repeats(plain(rows), anchors.Bytes, window, max(1, min(64, window // 4)), False, repeated(window), "op3")


def dedup(docs: DataFrame, window: int = 400) -> DataFrame:
    """Per document: bytes, removed bytes and spans, the bytes that are kept and their sha256."""

    def cut(batches):
        for b in batches:
            rows = []
            for doc, text, spans in zip(*(c.to_pylist() for c in b.columns), strict=True):
                raw = unpacked(text) if text is not None else b""
                gone = anchors.covered(len(raw), spans)
                kept = np.frombuffer(raw, np.uint8)[~gone].tobytes() if spans else raw
                rows.append((doc, len(raw), int(gone.sum()), int(np.count_nonzero(np.diff(gone.astype(np.int8), prepend=np.int8(0)) == 1)), hashlib.sha256(kept).hexdigest(), kept))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()), strict=True)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    rows = numbered(docs)
    spans = strings(rows, window).groupBy(F.col("doc_id").alias("row")).agg(F.collect_list(F.struct("start", "end")).alias("spans"))
    return rows.join(spans, "row", "left").select("doc_id", "packed", "spans").mapInArrow(lean(cut), SCHEMA)
