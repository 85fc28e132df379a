"""Mixture-controlled packing: deficit round-robin over source queues.

Every source has a queue of tokens. A window takes from each queue its share of 2,048 tokens plus the deficit it carries,
in whole tokens: after b windows queue q has given floor(b w C[q+1]) - floor(b w C[q]) tokens, C being the running sum of
the shares. This is what the round-robin serves, in closed form: deficits stay below one token, are carried over all
windows and partitions, and any task can tell the window of any token from its place in its queue. Places come from sums
for each part of the input, so that no text or token is shuffled. A queue that runs dry ends a phase; the shares of the
others are scaled up. Only the last window of all is not full.

Defined results: null text is empty and gives the end token alone; null source is a queue of its own; repeated rows are
packed each; `<|endoftext|>` inside a text is that one token, as the tokenizers library has it; an empty table gives no
rows; other columns are ignored, whatever their names. A very long text is encoded as a whole.
"""

from __future__ import annotations

import base64
import json
import re
import zlib
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tempcorr.llm.common import lean, written

END = 1
TOKENS = "doc_id long, source string, part int, before long, n int, ids binary"
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, source string"
#: Rows of (source, part) that are broadcast; more are joined by a shuffle.
MOST_BROADCAST = 200_000


class Encoder:
    """Ids by the byte-level vocabulary, remembered by words.

    Where all white space is single, the vocabulary's splitting pattern always begins a new part at a space, so that a
    text's ids are those of its words, each with the space before it. Other texts are encoded whole. The rank file has
    the vocabulary of byte_bpe_50k.json; tests hold the ids against the tokenizers library. special: a special token that
    stands in a text is that token, as the library has it unless encode_special_tokens is set; else it is text as any other.
    """

    LIMIT = 300_000
    UNEVEN = re.compile(r"\s\s|^ | $")

    def __init__(self, path: str | None = None, special: bool = False):
        import public_tokenizers as public
        import tiktoken

        with open(path or public.path("byte_bpe_50k.tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.whole = tiktoken.Encoding("own", pat_str=public.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.known: dict[str, bytes] = {}
        with open(public.path("byte_bpe_50k.json"), encoding="utf-8") as f:
            self.special = {x["content"]: np.array([x["id"]], np.uint16).tobytes() for x in json.load(f)["added_tokens"] if special}
        self.cut = re.compile("|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) or r"(?!)")

    def of(self, word: str) -> bytes:
        if len(self.known) >= self.LIMIT:
            self.known.clear()
        out = self.known[word] = np.array(self.whole(word), np.uint16).tobytes()
        return out

    def __call__(self, text: str) -> bytes:
        """Little-endian unsigned 16-bit ids."""
        if self.cut.search(text):
            parts = self.cut.split(text)
            between = [*map(self.special.__getitem__, self.cut.findall(text)), b""]
            return b"".join([x for part, token in zip(parts, between, strict=True) for x in (self.plain(part), token)])
        return self.plain(text)

    def plain(self, text: str) -> bytes:
        if not text:
            return b""
        if "\0" in text or self.UNEVEN.search(text):
            return np.array(self.whole(text), np.uint16).tobytes()
        first, *words = text.replace(" ", "\0 ").split("\0")
        known, of = self.known, self.of
        return self.of(first) + b"".join([known.get(w) or of(w) for w in words])


def tokenised(docs: DataFrame) -> DataFrame:
    """Ids of every document, and how many tokens its source had before it in its part of the input."""

    def run(batches):
        encode, part, before = Encoder(special=True), TaskContext.get().partitionId(), {}
        end = np.array([END], np.uint16).tobytes()
        for b in batches:
            rows = []
            for doc, text, source in zip(*(c.to_pylist() for c in b.columns), strict=True):
                ids = encode(text or "") + end
                n = len(ids) // 2
                rows.append((doc, source, part, before.get(source, 0), n, ids))
                before[source] = before.get(source, 0) + n
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.string(), pa.int32(), pa.int64(), pa.int32(), pa.binary()), strict=True)], ["doc_id", "source", "part", "before", "n", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("source").cast("string").alias("source")).mapInArrow(lean(run), TOKENS)


def phases(totals: list[int], weights: list[Fraction]) -> list[tuple[int, list[int], list[int]]]:
    """(tokens before, first token of each queue, tokens of each queue), one for each span between two queues' ends."""
    out, done, given = [], 0, [0] * len(totals)
    while any(g < t for g, t in zip(given, totals, strict=True)):
        live = [q for q, t in enumerate(totals) if given[q] < t]
        weight = {q: weights[q] for q in live}
        if not any(weight.values()):  # only queues that are not wanted are left
            weight = {q: Fraction(totals[q] - given[q]) for q in live}
        rate = min(Fraction(totals[q] - given[q]) / w for q, w in weight.items() if w)
        take = [0] * len(totals)
        for q, w in weight.items():
            take[q] = min(totals[q] - given[q], int(rate * w) if (totals[q] - given[q]) != rate * w else totals[q] - given[q])
        out.append((done, list(given), take))
        done += sum(take)
        given = [g + t for g, t in zip(given, take, strict=True)]
    return out


class Mixer:
    """Where the tokens of a queue go."""

    def __init__(self, plan, window: int):
        self.window = window
        self.plan = [(done, first, take, np.cumsum([0, *take]).tolist()) for done, first, take in plan]

    def places(self, queue: int, at: int, n: int):
        """(global place, tokens) for runs of the tokens at, ..., at + n - 1 of a queue."""
        w = self.window
        for done, first, take, cum in self.plan:
            low, high = max(at, first[queue]) - first[queue], min(at + n, first[queue] + take[queue]) - first[queue]
            if low >= high:
                continue
            total, c0, c1 = cum[-1], cum[queue], cum[queue + 1]

            def given(b, total=total, c0=c0, c1=c1):
                e = min(total, b * w)
                return e * c1 // total - e * c0 // total

            b = low * total // (take[queue] * w)
            while given(b) > low:
                b -= 1
            while given(b + 1) <= low:
                b += 1
            while low < high:
                s, e = given(b), given(b + 1)
                upto = min(e, high)
                if upto > low:
                    e0, e1 = min(total, b * w), min(total, (b + 1) * w)
                    place = done + b * w + (e1 * c0 // total - e0 * c0 // total) + (low - s)
                    while low < upto:  # a phase need not begin where a window begins
                        step = min(upto - low, w - place % w)
                        yield place, step
                        place, low = place + step, low + step
                b += 1


def pack(docs: DataFrame, window: int = 2048, targets: dict[str | None, float] | None = None) -> DataFrame:
    """Pieces of documents in windows of `window` tokens. targets: a weight for each source; the sources' own shares if None."""
    tokens = written(tokenised(docs), "op2-tokens")
    sums = written(tokens.groupBy("source", "part").agg(F.sum("n").alias("n")), "op2-sums")
    largest = sums.groupBy("source").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "source").collect()
    own = {r["source"]: q for q, r in enumerate(largest)}
    totals = [r["n"] for r in largest]
    weights = [Fraction(t) for t in totals] if targets is None else [Fraction(targets.get(s, 0)).limit_denominator(10**6) for s in own]
    mixer = Mixer(phases(totals, weights), window)
    queues = tokens.sparkSession.createDataFrame(list(own.items()), "of string, queue int")
    ordered = Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = sums.withColumn("base", F.coalesce(F.sum("n").over(ordered), F.lit(0))).join(queues, F.col("source").eqNullSafe(F.col("of"))).select(F.col("source").alias("s"), F.col("part").alias("p"), "queue", "base")
    if sums.count() <= MOST_BROADCAST:
        base = F.broadcast(base)
    placed = tokens.join(base, F.col("source").eqNullSafe(F.col("s")) & (F.col("part") == F.col("p"))).select("doc_id", "source", "queue", (F.col("base") + F.col("before")).alias("at"), "n", "ids")

    def run(batches):
        for b in batches:
            rows = []
            for doc, source, q, at, n, ids in zip(*(c.to_pylist() for c in b.columns), strict=True):
                wide, start = np.frombuffer(ids, np.uint16).astype("<u4"), 0
                for place, length in mixer.places(q, at, n):
                    rows.append((doc, start, length, zlib.crc32(wide[start : start + length]), n, place // window, place % window, source))
                    start += length
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.string() if i == 7 else pa.int64()) for i, c in enumerate(zip(*rows, strict=True))], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "source"])

    return placed.mapInArrow(lean(run), PIECES)
