"""Substring dedup: words of a passage that also starts in an earlier document are removed.

Reference shards are dealt by the anchors of their windows (see anchors.py), so that a window meets every window that can
equal it; a shard's passages go into a suffix automaton whose states know the smallest document of each match, and the
same passages are streamed through it for matching statistics. Broadcasting automata of the whole corpus to every task
would cost shards times documents; dealing by anchors sends each passage to the one shard that can hold its match.
Whole runs that repeat are settled by their hash before; strings of hot anchors meet window by window.

Defined results: null or empty text has no words and nothing removed; repeated rows of one doc_id are each compared with
smaller doc_ids only, and get the spans of all of them joined; a row without a doc_id has no order: it loses nothing and
others lose nothing by it; an empty table gives no rows; other columns are ignored, whatever their names. A very long text
is hashed in blocks and cut as a whole, in some 100 bytes of memory for each word.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr.llm import anchors
from tempcorr.llm.automaton import SuffixAutomaton
from tempcorr.llm.common import keyed, lean, unpacked

SCHEMA = "doc_id long, n_words long, n_removed long, kept_sha256 string, kept_text string"


def earlier(window: int):
    """Resolves a piece of open strings: the windows of each that also start in a smaller document.

    The window hashes of a whole piece show at once which stretches of which strings can match; only those go, each
    content once, into the automaton of their anchor, which decides.
    """

    def resolve(rows):
        count = np.array([r["windows"] for r in rows])
        size = count + window - 1
        words = anchors.WordPlaces(b" ".join([r["content"] for r in rows]))
        at = np.arange(count.sum()) + np.repeat(np.arange(len(rows)), count) * (window - 1)  # windows within a string
        _, known = np.unique(anchors.Rolling(anchors.word_hashes(words)).all(window)[at], return_inverse=True)
        owner = np.repeat(np.array([r["doc_id"] for r in rows]), count)
        low, high = np.full(len(at), np.iinfo(np.int64).max), np.full(len(at), np.iinfo(np.int64).min)
        np.minimum.at(low, known, owner)
        np.maximum.at(high, known, owner)
        twice = np.zeros(len(words) + 1, np.int8)
        twice[at[(low < high)[known]]] = 1
        edge = np.diff(twice, prepend=np.int8(0))
        begin, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        row = np.searchsorted(np.cumsum(size), begin, side="right")
        begun = (begin - (np.cumsum(size) - size)[row]).tolist()
        group: dict[bytes, list[tuple[int, int]]] = {}
        anchor = None
        for i, b, s, e in zip(row.tolist(), begun, begin.tolist(), end.tolist(), strict=True):
            if rows[i]["anchor"] != anchor:
                yield from matched(group)
                group, anchor = {}, rows[i]["anchor"]
            group.setdefault(words.words(s, e + window - 1), []).append((rows[i]["doc_id"], rows[i]["start"] + b))
        yield from matched(group)

    def matched(group: dict[bytes, list[tuple[int, int]]]):
        """Spans of the contents of one anchor, each with the (document, start) that have it."""
        machine = SuffixAutomaton()
        for content, places in group.items():
            machine.add(content.split(), min(places)[0])
        machine.finish()
        for content, places in group.items():
            least = list(machine.statistics(content.split(), window))[window - 1 :]
            for doc, start in places:
                begun = None
                for i, o in enumerate([*least, None]):
                    hit = o is not None and o < doc
                    if hit and begun is None:
                        begun = i
                    elif not hit and begun is not None:
                        yield doc, start + begun, start + i + window - 1
                        begun = None

    return resolve


def passages(docs: DataFrame, window: int = 13) -> DataFrame:
    """(doc_id, start, end): spans of words that repeat an earlier document."""
    return anchors.repeats(keyed(docs).where("doc_id is not null"), anchors.Words, window, min(4, window), True, earlier(window), "op4")


def dedup(docs: DataFrame, window: int = 13) -> DataFrame:
    """Per document: words, removed words, what is kept (joined by one space) and its sha256."""

    def cut(batches):
        for b in batches:
            rows = []
            for doc, text, spans in zip(*(c.to_pylist() for c in b.columns), strict=True):
                words = unpacked(text).split() if text is not None else []
                gone = anchors.covered(len(words), spans)
                kept = b" ".join([w for w, g in zip(words, gone.tolist(), strict=True) if not g] if spans else words)
                rows.append((doc, len(words), int(gone.sum()), hashlib.sha256(kept).hexdigest(), kept.decode()))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()), strict=True)], ["doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"])

    docs = keyed(docs)
    return anchors.with_spans(docs, passages(docs, window), cut, SCHEMA)


def without_passages(docs: DataFrame, window: int = 13) -> DataFrame:
    """The documents with repeated passages cut out of their text, which else stays as it is; what has no word left goes.

    All columns are kept; n_chars, where there is one, is counted anew.
    """
    per = passages(docs, window).groupBy("doc_id").agg(F.collect_list(F.struct("start", "end")).alias("_spans"))
    at = docs.columns.index("text")
    sized = docs.columns.index("n_chars") if "n_chars" in docs.columns else None
    joined = docs.join(per, "doc_id", "left").select(*docs.columns, "_spans")

    def run(batches):
        for b in batches:
            texts, keep = [], []
            for text, spans in zip(b.column(at).to_pylist(), b.column(b.num_columns - 1).to_pylist(), strict=True):
                stays = True
                if spans:
                    raw = text.encode()
                    places = anchors.WordPlaces(raw)
                    gone = anchors.covered(len(places), spans)
                    stays = not gone.all()
                    turn = np.diff(gone.astype(np.int8), prepend=np.int8(0), append=np.int8(0))
                    kept, last = [], 0
                    for s, e in zip(np.flatnonzero(turn == 1).tolist(), np.flatnonzero(turn == -1).tolist(), strict=True):
                        kept.append(raw[last : places.at[s]])
                        last = int(places.at[e]) if e < len(places) else len(raw)
                    text = b"".join([*kept, raw[last:]]).decode()
                texts.append(text)
                keep.append(stays)
            columns = list(b.columns[:-1])
            columns[at] = pa.array(texts, b.schema.field(at).type)
            if sized is not None:
                columns[sized] = pa.array([None if t is None else len(t) for t in texts], b.schema.field(sized).type)
            yield pa.RecordBatch.from_arrays(columns, b.schema.names[:-1]).filter(pa.array(keep, pa.bool_()))

    return joined.mapInArrow(lean(run), docs.schema)
