"""Scores by masked pseudo-likelihood: a bidirectional window network, trained in numpy over all documents.

Every word is predicted from two words on either side. The words before and after have embeddings of their own for each
place; their sum goes through tanh and a softmax in two steps, over classes and over the ids of a class.

All words are counted, each by its own 64-bit hash, in a distributed table that is as long as the corpus has words. The
most frequent words that make up COVER of all tokens have an id each, and the network is as large as that takes. Every
other word shares an id; its probability is that of the id times its part of the id's count, which is joined to the
documents from the table, so that the probabilities of all words of the corpus sum to one. In training every word of every document is
predicted once. Documents are dealt to shards by a hash of doc_id and text, as many as the corpus has words for; each shard
trains a copy of the network over its documents in order, and the copies are averaged, weighted by their words, by a tree
of tasks. How the input is cut into parts has no bearing on the result. Half of the shards are the first round, the others
the second. At last every word of every document is predicted.

Defined results: null or empty text has no words, log-probability 0 and a null mean; repeated rows are scored each; an
empty table gives no rows; other columns are ignored, whatever their names. A very long text is hashed in blocks; its ids
take some 40 bytes of memory for each word.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr.llm.anchors import WordPlaces, word_hashes
from tempcorr.llm.common import dropped, keyed, lean, mix, text_bytes, written

#: The part of all tokens whose words have an id of their own.
COVER = 0.5
CLASSES, SIDE = 32, 2
#: SIZE is even: see Network.train.
SIZE, RATE, ROUNDS = 24, 0.15, 2
#: Words of a training step, at first and at most; words that a copy of the network is trained on, about.
LEAST_BATCH, BATCH, SHARD = 2048, 16384, 2_000_000
EDGE = 0
FAN = 16
#: Logits whose bound is under this need no shift before their exponentials are taken in single precision.
SAFE = 60.0
#: Words whose counts a task adds up at once.
HELD = 1 << 22
OUT = "doc_id long, n_tokens long, log_prob double, mean_log_prob double"


def hashes_of(text: bytes | None) -> np.ndarray:
    """A 64-bit hash for each word."""
    places = WordPlaces(text or b"")
    if not len(places):
        return np.zeros(0, np.int64)
    return word_hashes(places).view(np.int64)


def word_counts(docs: DataFrame) -> DataFrame:
    """(word, n) over all words of all documents; a task adds up what it holds at HELD words."""

    def run(batches):
        held, size = [], 0

        def counted():
            word, n = np.unique(np.concatenate(held), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(word), pa.array(n)], ["word", "n"])

        for b in batches:
            for text in text_bytes(b.column(1)):
                held.append(hashes_of(text))
                size += len(held[-1])
                if size >= HELD:
                    yield counted()
                    held, size = [], 0
        if size:
            yield counted()

    return docs.mapInArrow(lean(run), "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))


class Vocabulary:
    """Ids of words: 0 is a text's edge, then the frequent words' own, then those that other words share."""

    def __init__(self, frequent: list[int]):
        """frequent: hashes of the words with an id of their own, the most frequent first."""
        self.classes = max(2, int(np.ceil(np.sqrt(1 + len(frequent) * 4 / 3))))
        self.own = len(frequent)
        self.shared = self.classes * self.classes - 1 - self.own
        words = np.array(frequent, np.int64)
        self.order = np.argsort(words)
        self.words = words[self.order]

    def __call__(self, words: np.ndarray) -> np.ndarray:
        ids = (1 + self.own + mix(words.view(np.uint64)) % np.uint64(self.shared)).astype(np.int32)
        if self.own:
            at = np.minimum(np.searchsorted(self.words, words), self.own - 1)
            ids = np.where(self.words[at] == words, (1 + self.order[at]).astype(np.int32), ids)
        return ids

    def is_shared(self, ids: np.ndarray) -> np.ndarray:
        return ids > self.own


def vocabulary(counts: DataFrame, cover: float = COVER) -> Vocabulary:
    """As many of the most frequent words as it takes to cover the tokens."""
    total, found = 0, []
    steps = counts.groupBy("n").agg(F.count("*").alias("words")).withColumn("tokens", F.col("n") * F.col("words")).orderBy(F.desc("n")).collect()
    every, least = sum(r["tokens"] for r in steps), None
    for r in steps:
        if total >= cover * every:
            break
        least, wanted = r["n"], -int(-(cover * every - total) // r["n"])
        total += r["tokens"]
    if least is not None:
        found = [r["word"] for r in counts.where(F.col("n") > least).orderBy(F.desc("n"), "word").collect()]
        found += [r["word"] for r in counts.where(F.col("n") == least).orderBy("word").limit(wanted).collect()]
    return Vocabulary(found)


def shares(counts: DataFrame, table: Vocabulary) -> DataFrame:
    """(word, share): the log of every other word's part of the count of its id."""

    def run(batches):
        for b in batches:
            ids = table(b.column(0).to_numpy())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(ids)], ["word", "n", "id"]).filter(pa.array(table.is_shared(ids)))

    others = counts.mapInArrow(lean(run), "word long, n long, id int")
    totals = others.groupBy("id").agg(F.sum("n").alias("all"))
    return others.join(F.broadcast(totals), "id").select("word", F.log(F.col("n") / F.col("all")).alias("share"))


def encoded(docs: DataFrame, table: Vocabulary, shards: int) -> DataFrame:
    """Every row's ids, and its distinct words that share an id; a row's key and shard follow from its doc_id and text alone.

    `row` tells rows apart. It is fixed with the written table, and rises along it, so that shuffles of it compress well.
    """
    kind = np.uint16 if table.classes**2 <= 1 << 16 else np.uint32

    def run(batches):
        for b in batches:
            ids, rare, times = [], [], []
            for text in text_bytes(b.column(2)):
                h = hashes_of(text)
                own = table(h)
                ids.append(own.astype(kind).tobytes())
                words, n = np.unique(h[table.is_shared(own)], return_counts=True)
                rare.append(words)
                times.append(n.astype(np.int32))
            cuts = pa.array(np.cumsum([0, *map(len, rare)]).astype(np.int32))
            flat = [np.concatenate([x, e]) for x, e in ((np.concatenate(rare), np.zeros(0, np.int64)), (np.concatenate(times), np.zeros(0, np.int32)))] if rare else [np.zeros(0, np.int64), np.zeros(0, np.int32)]
            lists = [pa.ListArray.from_arrays(cuts, pa.array(x)) for x in flat]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(3), b.column(4), pa.array(ids, pa.binary()), *lists], ["doc_id", "key", "shard", "row", "ids", "rare", "times"])

    key = F.xxhash64("doc_id", "text")
    rows = docs.select("doc_id", key.alias("key"), "text", F.pmod(F.xxhash64(key, F.lit(1)), F.lit(shards)).cast("int").alias("shard"), F.monotonically_increasing_id().alias("row"))
    return written(rows.mapInArrow(lean(run), "doc_id long, key long, shard int, row long, ids binary, rare array<bigint>, times array<int>"), "op8-ids")


def ids_of(raw: bytes, classes: int) -> np.ndarray:
    """The ids of a row, with SIDE edges at either end."""
    edge = np.full(SIDE, EDGE, np.int32)
    return np.concatenate([edge, np.frombuffer(raw, np.uint16 if classes**2 <= 1 << 16 else np.uint32).astype(np.int32), edge])


def within_ids(rows: DataFrame, counts: DataFrame, table: Vocabulary) -> DataFrame:
    """(row, within): the sum of the shares of a row's words with a shared id."""
    words = rows.select("row", F.explode(F.arrays_zip("rare", "times")).alias("w")).select("row", F.col("w.rare").alias("word"), F.col("w.times").alias("times"))
    return words.join(shares(counts, table).hint("shuffle_hash"), "word").groupBy("row").agg(F.sum(F.col("times") * F.col("share")).alias("within"))


def grouped(labels: np.ndarray, most: int) -> np.ndarray:
    """The stable order of labels under `most`; 16-bit ones are sorted by radix."""
    return np.argsort(labels.astype(np.uint16) if most <= 1 << 16 else labels, kind="stable")


class Network:
    """The window network; all its numbers in one array, so that copies can be averaged. It has classes * classes ids."""

    def __init__(self, flat: np.ndarray | None = None, classes: int = CLASSES):
        self.classes = classes
        shapes = ((2 * SIDE, classes * classes, SIZE), (SIZE,), (SIZE, classes), (classes,), (classes, SIZE, classes), (classes, classes))
        sizes = [int(np.prod(s)) for s in shapes]
        if flat is None:
            rng = np.random.default_rng(1)
            flat = (rng.standard_normal(sum(sizes)) * 0.05).astype(np.float32)
        self.flat = flat
        cuts = np.cumsum([0, *sizes])
        self.embed, self.shift, self.to_class, self.class_bias, self.to_word, self.word_bias = (flat[a:b].reshape(s) for a, b, s in zip(cuts[:-1], cuts[1:], shapes, strict=True))

    def hidden(self, context: np.ndarray) -> np.ndarray:
        """context: for each predicted word the ids around it."""
        h = self.embed[0].take(context[:, 0], 0)
        h += self.shift
        for j in range(1, 2 * SIDE):
            h += self.embed[j].take(context[:, j], 0)
        return np.tanh(h, out=h)

    def _by_class(self, h: np.ndarray, target: np.ndarray):
        """Tokens sorted by class: their order, where each class begins, and the logits of the ids of their classes."""
        cls = target // self.classes
        order = grouped(cls, self.classes)
        cuts = np.r_[0, np.cumsum(np.bincount(cls, minlength=self.classes))]
        h, logits = h.take(order, 0), np.empty((len(target), self.classes), np.float32)
        for c in range(self.classes):
            s, e = cuts[c], cuts[c + 1]
            if e > s:
                np.matmul(h[s:e], self.to_word[c], out=logits[s:e])
                logits[s:e] += self.word_bias[c]
        return order, cuts, h, logits

    def _safe(self) -> tuple[bool, bool]:
        """Whether the logits of classes, and of ids, are small for any hidden layer, all of whose numbers are within 1."""
        return tuple(float((np.abs(w).sum(-2) + np.abs(b)).max()) < SAFE for w, b in ((self.to_class, self.class_bias), (self.to_word, self.word_bias)))

    @staticmethod
    def _raised(logits: np.ndarray, safe: bool) -> np.ndarray:
        """Exponentials in place; the sum of each row."""
        if not safe:
            logits -= logits.max(1, keepdims=True)
        np.exp(logits, out=logits)
        return logits @ np.ones(logits.shape[1], np.float32)

    def _chosen(self, logits: np.ndarray, at: np.ndarray, safe: bool) -> np.ndarray:
        """The log-probability of one column of each row."""
        if not safe:
            logits -= logits.max(1, keepdims=True)
        own = logits[np.arange(len(at)), at].astype(np.float64)
        return own - np.log(self._raised(logits, True))

    def log_probs(self, context: np.ndarray, target: np.ndarray) -> np.ndarray:
        h = self.hidden(context)
        safe = self._safe()
        out = self._chosen(h @ self.to_class + self.class_bias, target // self.classes, safe[0])
        order, _, _, logits = self._by_class(h, target)
        out[order] += self._chosen(logits, target[order] % self.classes, safe[1])
        return out

    def _slope(self, logits: np.ndarray, at: np.ndarray, safe: bool) -> np.ndarray:
        """The slope of the loss in each logit: probabilities, less one at the right column."""
        logits *= (1 / self._raised(logits, safe))[:, None]
        logits[np.arange(len(at)), at] -= 1
        return logits

    def train(self, context: np.ndarray, target: np.ndarray, memory: np.ndarray) -> None:
        """One step with rates that fall as squared gradients add up."""
        grad = Network(np.zeros_like(self.flat), self.classes)
        h = self.hidden(context)
        safe = self._safe()
        p = self._slope(h @ self.to_class + self.class_bias, target // self.classes, safe[0])
        np.matmul(h.T, p, out=grad.to_class)
        grad.class_bias[:] = p.sum(0)
        back = p @ self.to_class.T
        order, cuts, sorted_h, logits = self._by_class(h, target)
        q = self._slope(logits, target[order] % self.classes, safe[1])
        part = np.empty_like(sorted_h)
        for c in range(self.classes):
            s, e = cuts[c], cuts[c + 1]
            if e > s:
                np.matmul(sorted_h[s:e].T, q[s:e], out=grad.to_word[c])
                grad.word_bias[c] = q[s:e].sum(0)
                np.matmul(q[s:e], self.to_word[c].T, out=part[s:e])
        back[order] += part
        back *= 1 - h * h
        grad.shift[:] = back.sum(0)
        for j in range(2 * SIDE):
            by = grouped(context[:, j], self.classes**2)
            ids = context[:, j].take(by)
            first = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
            # two numbers are added at once, as the parts of a complex one
            grad.embed[j][ids[first]] = np.add.reduceat(back.take(by, 0).view(np.complex64), first, axis=0).view(np.float32)
        g = grad.flat
        g /= np.float32(len(target))
        memory += g * g
        self.flat -= np.float32(RATE) * g / np.sqrt(memory + np.float32(1e-8))


def around(ids: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The ids before and after the places `at` of a text that has SIDE edges at either end."""
    return np.stack([ids[at + d] for d in (*range(-SIDE, 0), *range(1, SIDE + 1))]).T


def framed(text: bytes | None, table: Vocabulary) -> np.ndarray:
    edge = np.full(SIDE, EDGE, np.int32)
    return np.concatenate([edge, table(hashes_of(text)), edge])


def trained(rows: DataFrame, classes: int, start: Network | None, turn: int, shards: int) -> Network:
    """The average of copies that the shards of a round have trained, each over its rows in the order of doc_id and key."""
    begin = Network(None if start is None else start.flat.copy(), classes).flat
    mine = rows.where(F.pmod("shard", F.lit(ROUNDS)) == turn).select("shard", "doc_id", "key", "ids")
    dealt = mine.repartition(max(1, shards // ROUNDS) * 2, "shard").sortWithinPartitions("shard", "doc_id", "key")

    class Copy:
        def __init__(self):
            self.net, self.memory, self.steps, self.words = Network(begin.copy(), classes), np.zeros(len(begin), np.float32), 0, 0
            self.contexts, self.targets, self.held = [], [], 0

        def step(self):
            if self.held:
                self.net.train(np.concatenate(self.contexts), np.concatenate(self.targets), self.memory)
                self.contexts, self.targets, self.held = [], [], 0
                self.steps += 1

        def add(self, ids):
            n = len(ids) - 2 * SIDE
            self.words += n
            at, s = np.arange(SIDE, SIDE + n), 0
            while s < n:  # batches begin small and grow
                e = min(n, s + min(BATCH, LEAST_BATCH << (self.steps // 32)) - self.held)
                self.contexts.append(around(ids, at[s:e]))
                self.targets.append(ids[at[s:e]])
                self.held, s = self.held + e - s, e
                if self.held >= min(BATCH, LEAST_BATCH << (self.steps // 32)):
                    self.step()

    def run(batches):
        def out(shard, copy):
            copy.step()
            if copy.words:
                yield pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([copy.words], pa.int64()), pa.array([copy.net.flat.tobytes()], pa.binary())], ["part", "words", "net"])

        copy = last = None
        for b in batches:
            for shard, raw in zip(b.column(0).to_pylist(), b.column(3), strict=True):
                if shard != last:
                    if copy is not None:
                        yield from out(last, copy)
                    copy, last = Copy(), shard
                copy.add(ids_of(raw.as_py(), classes))
        if copy is not None:
            yield from out(last, copy)

    copies = copied = written(dealt.mapInArrow(lean(run), "part int, words long, net binary"), f"op8-copies{turn}")
    highest = shards - 1

    def average(batches):
        by: dict[int, list] = {}
        for b in batches:
            for part, words, net in zip(*(c.to_pylist() for c in b.columns), strict=True):
                total = by.setdefault(part, [0, np.zeros(len(begin))])
                total[0] += words
                total[1] += words * np.frombuffer(net, np.float32).astype(np.float64)
        for part, (words, total) in by.items():
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([words], pa.int64()), pa.array([(total / words).astype(np.float32).tobytes()], pa.binary())], ["part", "words", "net"])

    fan = F.floor(F.col("part") / FAN).cast("int")
    while highest >= FAN:
        highest //= FAN
        copies = copies.withColumn("part", fan).repartition(highest + 1, "part").sortWithinPartitions("part", "words").mapInArrow(lean(average), "part int, words long, net binary")
    got = sorted(copies.select("part", "words", "net").collect(), key=lambda r: (r["part"], r["words"]))  # FAN rows at most
    dropped(copied)
    total = sum(r["words"] for r in got)
    if not total:
        return Network(begin, classes)
    return Network((sum(r["words"] / total * np.frombuffer(r["net"], np.float32).astype(np.float64) for r in got)).astype(np.float32), classes)


def fitted(docs: DataFrame):
    """(rows as ids, counts of words, vocabulary, network) of all documents."""
    counts = written(word_counts(docs), "op8-counts")
    table = vocabulary(counts)
    tokens = counts.agg(F.sum("n").alias("n")).first()["n"] or 0
    shards = ROUNDS * max(1, -(-tokens // (ROUNDS * SHARD)))
    rows, net = encoded(docs, table, shards), None
    for turn in range(ROUNDS):
        net = trained(rows, table.classes, net, turn, shards)
    return rows, counts, table, net


def score(docs: DataFrame) -> DataFrame:
    """Rows of OUT: the sum and mean of every document's conditional log-probabilities."""
    rows, counts, table, net = fitted(keyed(docs))
    flat, classes = net.flat, table.classes

    def run(batches):
        net = Network(flat, classes)
        for b in batches:
            ids = [ids_of(x.as_py(), classes) for x in b.column(2)]
            sizes = np.array([len(x) - 2 * SIDE for x in ids])
            sums, doc, held = np.zeros(len(ids)), [], []

            def flush(doc, held, sums):
                logs = net.log_probs(np.concatenate([c for c, _ in held]), np.concatenate([t for _, t in held]))
                np.add.at(sums, np.concatenate(doc), logs)

            waiting = 0
            for i, x in enumerate(ids):
                at = np.arange(SIDE, SIDE + sizes[i])
                for s in range(0, len(at), BATCH):
                    held.append((around(x, at[s : s + BATCH]), x[at[s : s + BATCH]]))
                    doc.append(np.full(len(held[-1][1]), i))
                    waiting += len(held[-1][1])
                    if waiting >= BATCH // 2:
                        flush(doc, held, sums)
                        doc, held, waiting = [], [], 0
            if held:
                flush(doc, held, sums)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(sizes.astype(np.int64)), pa.array(sums)], ["doc_id", "row", "n_tokens", "log_prob"])

    scored = rows.select("doc_id", "row", "ids").mapInArrow(lean(run), "doc_id long, row long, n_tokens long, log_prob double")
    both = scored.join(within_ids(rows, counts, table), "row", "left")
    log_prob = F.col("log_prob") + F.coalesce("within", F.lit(0.0))
    return both.select("doc_id", "n_tokens", log_prob.alias("log_prob"), F.when(F.col("n_tokens") > 0, log_prob / F.col("n_tokens")).alias("mean_log_prob"))
