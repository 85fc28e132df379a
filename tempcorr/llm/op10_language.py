"""Language identification by interpolated Kneser-Ney models over characters, one for each language.

Texts are lowered; every run of what is no letter is one space. N-grams are packed into integers, which serve as perfect
hashes; the probabilities of all languages stand beside each other in arrays sorted by them, so that one search serves
all languages. The language of the lowest cross-entropy for a character wins. Its score is its share among the languages
(a softmax over the whole text's log-likelihoods, tempered) times the acceptance of its cross-entropy. That is calibrated on
a fifth of the sample, which the models don't learn: a text is rejected whose cross-entropy lies one spread or more
above the largest there.

The models are fitted on a sample of at most about MOST_DOCUMENTS labelled documents for each language, taken by a hash
of doc_id. Everything else covers all rows.

Defined results: null text or text without a letter is `und` with score 0; without any labelled text all is `und`;
repeated rows are judged each; an empty table gives no rows; other columns are ignored, whatever their names. A very long
text is judged in blocks.
"""

from __future__ import annotations

import math
from collections import defaultdict
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tempcorr.llm.common import bounded, lean

#: The bound of the fitted sample: labelled documents of a language.
MOST_DOCUMENTS = 1500
#: Bits of a symbol: space, others, and every letter of the sample (the most frequent 65,534, should it have more).
BITS = 16
ORDER = 4
#: Labelled documents from which on a fifth of a language's sample is not learned but calibrates its rejection.
LEAST_MEASURED = 20
UND = "und"
OUT = "doc_id long, lang_pred string, score double, cross_entropy double"
#: Texts are judged in blocks of so many characters, whose sums are added.
BLOCK = 1 << 20


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


@cache
def is_letter() -> np.ndarray:
    """Of every code point."""
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


class Letters:
    """Texts as arrays of symbols."""

    def __init__(self, alphabet: str):
        self.table = is_letter().astype(np.uint16)
        for i, c in enumerate(alphabet):
            self.table[ord(c)] = i + 2

    @staticmethod
    def plain(text: str) -> np.ndarray:
        return np.frombuffer(text.lower().encode("utf-32-le", "replace"), np.uint32)

    def __call__(self, text: str) -> np.ndarray:
        """Symbols with a space before and after; empty if there is no letter."""
        s = self.table[self.plain(text)]
        keep = np.ones(len(s), bool)
        keep[1:] = (s[1:] != 0) | (s[:-1] != 0)
        s = s[keep]
        if not s.any():
            return s[:0]
        return np.r_[np.uint16(0), s[1:] if s[0] == 0 else s, np.zeros(int(s[-1] != 0), np.uint16)]


def packing(bits: int) -> type:
    return np.uint32 if bits * ORDER <= 32 else np.uint64


def grams(s: np.ndarray, n: int, bits: int = 8) -> np.ndarray:
    kind = packing(bits)
    m = len(s) - n + 1
    if m <= 0:
        return np.zeros(0, kind)
    out = s[:m].astype(kind)
    for j in range(1, n):
        out = (out << kind(bits)) | s[j : j + m]
    return out


class KneserNey:
    """Natural-log probabilities of all n-grams of a sample, interpolated down to letters."""

    def __init__(self, counts: dict[int, int], bits: int = 8, symbols: int = 256):
        kind = packing(bits)
        self.shift, self.masks = kind(bits), [kind((1 << (bits * n)) - 1) for n in range(ORDER)]
        keys = np.array(sorted(counts), kind)
        n = np.array([counts[k] for k in keys.tolist()], np.float64)
        self.symbols = symbols
        self.tables = {}
        stack = []
        for order in range(ORDER, 0, -1):
            stack.append((order, keys, n))
            if order > 1:  # continuation counts: how many different symbols stand before a shorter n-gram
                keys, n = np.unique(keys & self.masks[order - 1], return_counts=True)
                n = n.astype(np.float64)
        lower_keys, lower = None, None
        for order, keys, n in reversed(stack):
            once, twice = (n == 1).sum(), (n == 2).sum()
            d = min(0.95, max(0.1, once / (once + 2 * twice))) if once else 0.5
            context = keys >> self.shift
            found, at = np.unique(context, return_inverse=True)
            total, kinds = np.bincount(at, n), np.bincount(at)
            gamma = d * kinds / total
            if order == 1:
                base = np.full(len(keys), 1 / self.symbols)
            else:
                short = keys & self.masks[order - 1]
                base = lower[np.searchsorted(lower_keys, short)]
            p = np.maximum(n - d, 0) / total[at] + gamma[at] * base
            self.tables[order] = (keys, p, found, gamma)
            lower_keys, lower = keys, p

    def probability(self, key: np.ndarray, order: int) -> np.ndarray:
        """Of any n-grams of an order, seen or not."""
        if order == 0:
            return np.full(len(key), 1 / self.symbols)
        keys, p, contexts, gamma = self.tables[order]
        i = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
        out, miss = p[i].copy(), keys[i] != key
        if miss.any():
            k = key[miss]
            short = k & self.masks[order - 1] if order > 1 else k
            rest = self.probability(short, order - 1)
            c = k >> self.shift
            j = np.minimum(np.searchsorted(contexts, c), len(contexts) - 1)
            out[miss] = np.where(contexts[j] == c, gamma[j], 1.0) * rest
        return out


class Judge:
    """The models of all languages side by side."""

    def __init__(self, alphabet: str, models: dict[str, KneserNey]):
        self.letters, self.names = Letters(alphabet), sorted(models)
        models = [models[x] for x in self.names]
        self.keys, self.logs = {}, {}
        for order in (2, 3, 4):
            self.keys[order] = np.unique(np.concatenate([m.tables[order][0] for m in models]))
            self.logs[order] = np.stack([np.log(m.probability(self.keys[order], order)) for m in models], 1).astype(np.float32)
        single = np.arange(len(alphabet) + 2, dtype=packing(BITS))
        self.single = np.stack([np.log(m.probability(single, 1)) for m in models], 1).astype(np.float32)
        self.back = {}
        for order in (2, 3, 4):  # what remains for unseen symbols after a context
            contexts = np.unique(np.concatenate([m.tables[order][2] for m in models]))
            rest = np.zeros((len(contexts) + 1, len(models)), np.float32)
            for j, m in enumerate(models):
                _, _, found, gamma = m.tables[order]
                rest[np.searchsorted(contexts, found), j] = np.log(gamma)
            self.back[order] = (contexts, rest)
        self.typical: dict[str, tuple[float, float, float]] = {}

    def log_likelihoods(self, s: np.ndarray) -> np.ndarray:
        """Of each language; the sum over all characters after the first three."""
        kind, total = packing(BITS), np.zeros(len(self.names))
        key = grams(s, 4, BITS)
        for order in (4, 3, 2):
            keys = self.keys[order]
            i = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
            seen = keys[i] == key
            total += self.logs[order][i[seen]].sum(0, dtype=np.float64)
            key = key[~seen]
            if not len(key):
                return total
            contexts, rest = self.back[order]
            c = key >> kind(BITS)
            j = np.minimum(np.searchsorted(contexts, c), len(contexts) - 1)
            total += rest[np.where(contexts[j] == c, j, len(contexts))].sum(0, dtype=np.float64)
            key = key & kind((1 << (BITS * (order - 1))) - 1)
        return total + self.single[key].sum(0, dtype=np.float64)

    def entropies(self, text: str):
        """(log-likelihoods, characters)."""
        total, n = np.zeros(len(self.names)), 0
        for b in range(0, len(text), BLOCK):
            s = self.letters(text[b : b + BLOCK])
            if len(s):
                s = np.r_[np.zeros(2, np.uint16), s]
                total += self.log_likelihoods(s)
                n += len(s) - 3
        return total, n

    def __call__(self, text: str | None) -> tuple[str, float, float | None]:
        total, n = self.entropies(text) if text and self.names else (None, 0)
        if n <= 0:
            return UND, 0.0, None
        best = int(total.argmax())
        share = 1 / np.exp(np.maximum((total - total[best]) / max(1.0, math.sqrt(n) / 4), -700)).sum()
        h = -total[best] / n
        mean, spread, limit = self.typical[self.names[best]]
        beyond = (h - mean) / (spread * widened(n)) - limit  # at one spread beyond the limit the score is under 0.02
        return self.names[best], float(share / (1 + math.exp(max(-50.0, min(50.0, 4 * beyond))))), float(h)


def sample(docs: DataFrame, most: int = MOST_DOCUMENTS) -> DataFrame:
    """(lang, text, measured): about `most` labelled texts of each language by a hash of doc_id, none of them held out."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id")))
    sizes = labelled.groupBy("lang").agg(F.count("*").alias("_n"))  # a row for each language
    part = F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) * F.col("_n") < F.lit(most * 1_000_000)
    return labelled.join(F.broadcast(sizes), "lang").where(part).select("lang", "text", ((F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(5)) == 0) & (F.col("_n") >= LEAST_MEASURED)).alias("measured"))


def fit(docs: DataFrame, most: int = MOST_DOCUMENTS) -> Judge:
    """Models from n-gram counts of the sample; the counts come to the driver, and are bounded by the sample's size."""
    chosen = sample(docs, most)

    def letters(batches):
        for b in batches:
            got: dict[int, int] = defaultdict(int)
            for text in b.column(1).to_pylist():
                for c, n in zip(*(x.tolist() for x in np.unique(Letters.plain(text), return_counts=True)), strict=True):
                    got[c] += n
            yield pa.RecordBatch.from_arrays([pa.array(got.keys(), pa.int64()), pa.array(got.values(), pa.int64())], ["c", "n"])

    found = chosen.mapInArrow(lean(letters), "c long, n long").groupBy("c").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "c").collect()
    alphabet = "".join([chr(r["c"]) for r in found if chr(r["c"]).isalpha()][: (1 << BITS) - 2])

    def count(batches):
        known = Letters(alphabet)
        held: dict[str, list] = defaultdict(list)
        for b in batches:
            for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                s = known(text)
                if len(s):
                    held[lang].append(grams(np.r_[np.zeros(2, np.uint16), s], ORDER, BITS))
        for lang, parts in held.items():
            k, n = np.unique(np.concatenate(parts), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(k)), pa.array(k.view(np.int64)), pa.array(n)], ["lang", "k", "n"])

    counts: dict[str, dict[int, int]] = defaultdict(dict)
    for r in chosen.where("not measured").mapInArrow(lean(count), "lang string, k long, n long").groupBy("lang", "k").agg(F.sum("n").alias("n")).toLocalIterator():
        counts[r["lang"]][r["k"] & 0xFFFFFFFFFFFFFFFF] = r["n"]
    judge = Judge(alphabet, {x: KneserNey(c, BITS, len(alphabet) + 2) for x, c in counts.items()}) if counts else Judge.__new__(Judge)
    if not counts:
        judge.names, judge.typical = [], {}
        return judge

    def entropy(batches):
        for b in batches:
            rows = []
            for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                total, n = judge.entropies(text)
                if n > 0 and lang in judge.names:
                    rows.append((lang, float(-total[judge.names.index(lang)] / n), n))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], kind) for i, kind in enumerate((pa.string(), pa.float64(), pa.int64()))], ["lang", "h", "n"])

    measured: dict[str, list[tuple[float, int]]] = defaultdict(list)
    for r in chosen.where("measured").mapInArrow(lean(entropy), "lang string, h double, n long").toLocalIterator():
        measured[r["lang"]].append((r["h"], r["n"]))  # as many as the sample's bound allows
    judge.typical = {x: limits(measured[x]) for x in judge.names}
    return judge


def limits(found: list[tuple[float, int]]) -> tuple[float, float, float]:
    """(mean, spread, limit) of cross-entropies of texts of a language that its model has not seen.

    The limit is what no such text exceeds, in spreads that are wider for short texts. Without such texts none is set.
    """
    if not found:
        return 0.0, 1.0, math.inf
    h, n = (np.array(x, float) for x in zip(*found, strict=True))
    mean = float(np.average(h, weights=np.minimum(n, 2000)))
    spread = max(0.05, float(np.median(np.abs(h - mean))) * 1.5)
    return mean, spread, float(max(1.0, ((h - mean) / (spread * widened(n))).max()))


def widened(n):
    return 1 + 8 / np.sqrt(n)


def identify(docs: DataFrame, most: int = MOST_DOCUMENTS) -> DataFrame:
    """Rows of OUT for every document. Fits on `doc_id`, `text` and `lang`; judges by the text alone."""
    bounded(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    judge = fit(docs, most)

    def run(batches):
        for b in batches:
            rows = [(doc, *judge(text)) for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.string(), pa.float64(), pa.float64()), strict=True)], ["doc_id", "lang_pred", "score", "cross_entropy"])

    return docs.select("doc_id", "text").mapInArrow(lean(run), OUT)


def accepted(docs: DataFrame, least: float = 0.02, most: int = MOST_DOCUMENTS) -> DataFrame:
    """The documents whose language is told with a score of `least` or more, with all their columns."""
    bounded(docs.sparkSession)
    judge = fit(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")), most)
    at = docs.columns.index("text")

    def run(batches):
        for b in batches:
            yield b.filter(pa.array([(r := judge(t))[0] != UND and r[1] >= least for t in b.column(at).to_pylist()], pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)
