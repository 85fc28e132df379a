"""MinHash near-duplicates by a multi-index Hamming join of b-bit signatures.

A document's shingle set has a signature of 64 symbols of 16 bits. Sets of a similarity of at least 0.85 differ in at most
25 symbols but for about one pair in a million. The signature is split into 13 chunks; of 25 differences some chunk has
at most one, so that each chunk is indexed once for every symbol left out, and two sets that agree in all others meet.
This finds every pair under the distance threshold. For another similarity the symbols that may differ and the chunks are
counted anew. Pairs are confirmed on the full sets.

Equal sets are one class, and only classes are compared. A bucket is not turned into all its pairs: its members are
first compared with one centre, the member that meets most others over all its buckets. Buckets whose members are then in
one component are done. In the others, members of one group (those whose best centre is the same) are compared in tiles of
two blocks: first by their signatures, then, what some member of another component may be linked with, on full sets.
Members of different groups are compared pair by pair, in a bucket of more than SMALL in tiles again. So no link that
could join two components is lost, and no step makes all pairs of a large group as rows.

Defined results: null text, empty text or text of white space has an empty set, links with nothing and is kept; repeated
rows are in one class; a row without a doc_id links nothing and is kept; ties are broken by the smallest doc_id; an empty table gives no rows; other columns are ignored,
whatever their names. A very long text is hashed in blocks; its set takes about 40 bytes of memory for each word.
"""

from __future__ import annotations

from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr.llm.anchors import WordPlaces, word_hashes, zipped
from tempcorr.llm.common import dropped, keyed, lean, mix, partitions, text_bytes, unpacked, written
from tempcorr.llm.components import components

SYMBOLS, SHINGLE, SIMILAR = 64, 3, 85
#: The part of pairs at the threshold that may be missed.
MISSED = 1.3e-6


def most_different(similar: int) -> int:
    """Symbols in which signatures of sets of this similarity, in percent, differ at most but for MISSED of the pairs."""
    j = similar / 100
    chance = [comb(SYMBOLS, k) * (1 - j) ** k * j ** (SYMBOLS - k) for k in range(SYMBOLS + 1)]
    return next(d for d in range(SYMBOLS + 1) if sum(chance[d + 1 :]) <= MISSED)


def bounds(most: int) -> list[int]:
    """Where chunks begin and end: so many that of `most` differences some chunk has at most one."""
    chunks = min(SYMBOLS // 2, most // 2 + 1)
    return [round(i * SYMBOLS / chunks) for i in range(chunks + 1)]


MOST_DIFFERENT = most_different(SIMILAR)
#: Members of a block of signatures, and of a block of full sets, which has about so many bytes at most; a tile has two blocks.
BLOCK, SETS_BLOCK, SETS_BYTES = 1024, 256, 4 << 20
#: Members of a bucket of several groups whose pairs are made as rows; a larger bucket goes in tiles.
SMALL = 128
#: Bits of a filter for each id, bits that stand for an id, and bits at most (8 MB).
FILTER_BITS, FILTER_PLACES, FILTER_MOST = 16, 4, 1 << 26
LOWER = bytes(x + 32 if 65 <= x <= 90 else x for x in range(256))
FACTORS = mix(np.arange(1, SYMBOLS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
SETS = "doc_id long, text_key long, n_shingles long, s1 long, s2 long, signature binary"


def shingles(text: bytes | None, size: int = SHINGLE) -> np.ndarray:
    """The sorted 64-bit hashes of a text's distinct shingles."""
    places = WordPlaces((text or b"").translate(LOWER))
    if not len(places):
        return np.zeros(0, np.uint64)
    h = word_hashes(places)
    k = min(size, len(h))
    n = len(h) - k + 1
    out = np.full(n, k, np.uint64)
    for j in range(k):
        out = mix(out + h[j : j + n])
    return np.unique(out)


def signature(s: np.ndarray) -> bytes:
    low = np.full(SYMBOLS, np.iinfo(np.uint64).max, np.uint64)
    for b in range(0, len(s), 1 << 14):
        part = s[b : b + (1 << 14)]
        for k in range(SYMBOLS):
            low[k] = min(low[k], (part * FACTORS[k]).min())
    return (mix(low) & np.uint64(0xFFFF)).astype(np.uint16).tobytes()


def sketches(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """Rows of SETS: the size of each set, two hashes of the whole set, and its signature."""

    def run(batches):
        for b in batches:
            rows = []
            for doc, key, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), text_bytes(b.column(2)), strict=True):
                s = shingles(text, size)
                rows.append((doc, key, len(s), int(s.sum(dtype=np.uint64).view(np.int64)), int(np.bitwise_xor.reduce(mix(s ^ np.uint64(0xA5A5A5A5A5A5A5A5))).view(np.int64)) if len(s) else 0, signature(s) if len(s) else None))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()), strict=True)], ["doc_id", "text_key", "n_shingles", "s1", "s2", "signature"])

    return docs.select("doc_id", F.xxhash64("text").alias("text_key"), "text").mapInArrow(lean(run), SETS)


def indexed(classes: DataFrame, most: int = MOST_DIFFERENT) -> DataFrame:
    """(key, rep): every chunk of a signature with each of its symbols left out; sets that differ in `most` symbols or fewer meet."""
    cuts = bounds(most)

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            reps = b.column(0).to_numpy()
            sig = np.frombuffer(b"".join(b.column(1).to_pylist()), np.uint16).reshape(-1, SYMBOLS).astype(np.uint64)
            keys = []
            for low, high in zip(cuts[:-1], cuts[1:], strict=True):
                for out in range(low, high):
                    h = np.full(len(sig), out + 1, np.uint64)
                    for j in range(low, high):
                        if j != out:
                            h = mix(h + sig[:, j])
                    keys.append(h)
            yield pa.RecordBatch.from_arrays([pa.array(np.stack(keys, 1).ravel().view(np.int64)), pa.array(np.repeat(reps, SYMBOLS))], ["key", "rep"])

    return classes.select("rep", "signature").mapInArrow(lean(run), "key long, rep long")


def different(a: bytes, b: bytes) -> int:
    return int((np.frombuffer(a, np.uint16) != np.frombuffer(b, np.uint16)).sum())


def near(pairs: DataFrame, classes: DataFrame, similar: int) -> DataFrame:
    """Those of the pairs (a, b) whose sizes and signatures allow a link."""
    most = most_different(similar)
    side = classes.select("rep", "n_shingles", "signature")
    both = pairs.join(side.toDF("a", "na", "siga"), "a").join(side.toDF("b", "nb", "sigb"), "b").where(100 * F.least("na", "nb") >= similar * F.greatest("na", "nb"))

    def run(batches):
        for t in batches:
            if t.num_rows:
                x, y = (np.frombuffer(b"".join(t.column(c).to_pylist()), np.uint16).reshape(-1, SYMBOLS) for c in (2, 3))
                yield pa.RecordBatch.from_arrays([t.column(0), t.column(1)], ["a", "b"]).filter(pa.array((x != y).sum(1) <= most))

    return both.select("a", "b", "siga", "sigb").mapInArrow(lean(run), "a long, b long")


def filter_places(ids: np.ndarray, bits: int) -> list[np.ndarray]:
    """The bits, of a power of two, that stand for each id."""
    return [mix(ids.view(np.uint64) * FACTORS[j] + FACTORS[j + 1]) & np.uint64(bits - 1) for j in range(FILTER_PLACES)]


def id_filter(ids: DataFrame) -> np.ndarray:
    """64-bit words of a filter that each of the (doc_id) passes, and few others; its size is bounded, and a fuller one lets more pass."""
    bits = 64
    while bits < min(FILTER_MOST, FILTER_BITS * ids.count()):
        bits *= 2

    def run(batches):
        for b in batches:
            at = np.concatenate(filter_places(b.column(0).to_numpy(), bits))
            yield pa.RecordBatch.from_arrays([pa.array((at >> np.uint64(6)).view(np.int64)), pa.array((np.uint64(1) << (at & np.uint64(63))).view(np.int64))], ["word", "mask"])

    found = ids.mapInArrow(lean(run), "word long, mask long").groupBy("word").agg(F.bit_or("mask").alias("mask")).toArrow()
    words = np.zeros(bits // 64, np.uint64)
    words[found.column("word").to_numpy()] = found.column("mask").to_numpy().view(np.uint64)
    return words


def passing(ids: np.ndarray, words: np.ndarray) -> np.ndarray:
    """Which of the ids pass a filter."""
    out = np.ones(len(ids), bool)
    for at in filter_places(ids, len(words) * 64):
        out &= (words[at >> np.uint64(6)] >> (at & np.uint64(63))) & np.uint64(1) > 0
    return out


def passed(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The documents that an id_filter of the given ids lets pass: all of those ids, and few others."""
    words = id_filter(ids)

    def run(batches):
        for b in batches:
            yield b.filter(pa.array(passing(b.column(0).to_numpy(), words)))

    return docs.where("doc_id is not null").select("doc_id", "text").mapInArrow(lean(run), "doc_id long, text string")


def full_sets(docs: DataFrame, ids: DataFrame, size: int, name: str) -> DataFrame:
    """(doc_id, items): the full sets of the given documents, made anew from their texts; no other text is shuffled but what passes the filter."""

    def sets(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([shingles(unpacked(t), size).tobytes() if t is not None else b"" for t in b.column(1).to_pylist()], pa.binary())], ["doc_id", "items"])

    ids = written(ids, f"{name}-ids")
    out = written(zipped(passed(docs, ids)).join(ids, "doc_id").dropDuplicates(["doc_id"]).mapInArrow(lean(sets), "doc_id long, items binary"), f"{name}-sets")
    dropped(ids)
    return out


def confirmed(pairs: DataFrame, items: DataFrame, similar: int, name: str) -> DataFrame:
    """Those of the pairs that are similar on their full sets, which are rows (doc_id, items)."""
    both = pairs.join(items.toDF("b", "y"), "b").join(items.toDF("a", "x"), "a").select("a", "b", "x", "y")

    def run(batches):
        for t in (b.slice(i, 512) for b in batches for i in range(0, b.num_rows, 512)):
            keep = []
            for x, y in zip(t.column(2).to_pylist(), t.column(3).to_pylist(), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                common = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * common >= similar * (len(x) + len(y) - common))
            yield pa.RecordBatch.from_arrays([t.column(0), t.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return written(both.mapInArrow(lean(run), "a long, b long"), f"{name}-links")


def common_items(sets: list[np.ndarray]) -> np.ndarray:
    """The sizes of all intersections, by products of slices of the membership matrix."""
    owner = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    _, item, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = times[item] > 1
    owner, item = owner[shared], np.unique(item[shared], return_inverse=True)[1]
    order = np.argsort(item, kind="stable")
    owner, item = owner[order], item[order]
    out = np.zeros((len(sets), len(sets)), np.float32)
    for low in range(0, int(item[-1]) + 1 if len(item) else 0, 4096):
        a, b = np.searchsorted(item, [low, low + 4096])
        m = np.zeros((len(sets), 4096), np.float32)
        m[owner[a:b], item[a:b] - low] = 1
        out += m @ m.T
    return out


def candidates(sig: np.ndarray, size: np.ndarray, label: np.ndarray, block: np.ndarray, similar: int) -> np.ndarray:
    """Rows (i, j), i < j, of a tile's members of different labels whose sizes and signatures allow a link.

    In a tile of two blocks only pairs across them; the pairs of a block are those of its tile with itself.
    """
    most, out = most_different(similar), [np.zeros((0, 2), np.int64)]
    two = block.min() != block.max()
    for i in range(len(sig) - 1):
        rest = slice(i + 1, None)
        j = np.flatnonzero((label[rest] != label[i]) & (100 * np.minimum(size[rest], size[i]) >= similar * np.maximum(size[rest], size[i])) & ((block[rest] != block[i]) | (not two))) + i + 1
        if len(j):
            j = j[(sig[j] != sig[i]).sum(1) <= most]
            if len(j):
                out.append(np.stack([np.full(len(j), i), j], 1))
    return np.concatenate(out)


def tile_links(pairs: np.ndarray, sets: list[np.ndarray], label: np.ndarray, similar: int):
    """Those of the pairs (i, j) that are similar on their full sets and join two components of the tile: as many as it takes."""
    up = {x: x for x in label.tolist()}

    def root(x):
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    used, at = np.unique(pairs, return_inverse=True)
    at = at.reshape(pairs.shape)
    size = [len(sets[x]) for x in used.tolist()]
    common = common_items([sets[x] for x in used.tolist()]) if len(pairs) > 20 * len(used) else None
    for (i, j), (p, q) in zip(pairs.tolist(), at.tolist(), strict=True):
        x, y = root(int(label[i])), root(int(label[j]))
        if x != y:
            both = int(common[p, q]) if common is not None else len(np.intersect1d(sets[i], sets[j], assume_unique=True))
            if 100 * both >= similar * (size[p] + size[q] - both):
                up[x] = y
                yield i, j


def unresolved(left: DataFrame, classes: DataFrame, docs: DataFrame, size: int, similar: int) -> DataFrame:
    """Links between the components that meet in buckets (key, rep, label, grp).

    A group's members are compared in tiles. What a bucket has of several groups is compared pair by pair where it has
    SMALL members at most, so that a member meets no more than that; a larger bucket is a group of its own, in tiles too.
    """
    several = left.groupBy("key").agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("rep")).alias("h1"), F.bit_xor(F.xxhash64("rep", F.lit(1))).alias("h2"), F.min("grp").alias("low"), F.max("grp").alias("high")).where("low < high")
    several = written(several.groupBy("n", "h1", "h2").agg(F.min("key").alias("key")).select("key", "n"), "op7-several")  # equal buckets are one
    own = left.select("rep", F.struct(F.lit(0).alias("kind"), F.col("grp").alias("id")).alias("grp"), "label")
    large = left.join(several.where(F.col("n") > SMALL), "key").select("rep", F.struct(F.lit(1).alias("kind"), F.col("key").alias("id")).alias("grp"), "label")
    members = written(compared(written(own.unionByName(large).distinct(), "op7-members"), classes, similar), "op7-alike")
    small = left.join(several.where(F.col("n") <= SMALL).select("key"), "key")
    one, two = small.toDF("key", "rep", "x", "g"), small.toDF("key", "c", "y", "h")
    pairs = one.join(two, "key").where("x < y and g <> h").select(F.least("rep", "c").alias("a"), F.greatest("rep", "c").alias("b")).distinct()
    pairs = written(near(pairs, classes, similar), "op7-1-pairs")
    ids = members.select(F.col("rep").alias("doc_id")).union(pairs.select("a")).union(pairs.select("b")).distinct()
    items = full_sets(docs, ids, size, "op7-1")
    links = within_groups(members, items, similar).unionByName(confirmed(pairs, items, similar, "op7-1"))
    out = written(links, "op7-1-found")
    dropped(several, members, pairs, items)
    return out


def tiled(members: DataFrame, sizes: DataFrame, *payload: str) -> DataFrame:
    """members (grp, rep, label, payload) dealt to tiles: every pair of a group's blocks. sizes: (grp, blocks)."""
    dealt = members.join(sizes, "grp").withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    tile = F.explode(F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda j: F.struct(F.least("block", j).alias("lo"), F.greatest("block", j).alias("hi"))))
    dealt = dealt.select("grp", tile.alias("tile"), "block", "rep", "label", *payload).select("grp", "tile.lo", "tile.hi", "block", "rep", "label", *payload)
    keys = ["grp", "lo", "hi"]
    return dealt.repartition(partitions(members.sparkSession), *keys).sortWithinPartitions(*keys)


def by_tile(batches):
    """The rows of each tile, as columns."""
    held = []
    for b in (b.slice(i, 256) for b in batches for i in range(0, b.num_rows, 256)):
        for row in b.to_pylist():
            if held and any(row[c] != held[-1][c] for c in ("grp", "lo", "hi")):
                yield held
                held = []
            held.append(row)
    if held:
        yield held


def columns(rows):
    return np.frombuffer(b"".join([r["signature"] for r in rows]), np.uint16).reshape(-1, SYMBOLS), *(np.array([r[c] for r in rows]) for c in ("n_shingles", "label", "block"))


def compared(members: DataFrame, classes: DataFrame, similar: int) -> DataFrame:
    """The members (grp, rep, label) that some member of their group and of another label may be linked with.

    Their signatures alone are dealt to tiles, a row of some 150 bytes for every BLOCK members of a group.
    """
    sizes = members.groupBy("grp").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"), F.min("label").alias("low"), F.max("label").alias("high")).where("low < high").drop("low", "high")
    rows = members.join(classes.select("rep", "n_shingles", "signature"), "rep").select("grp", "rep", "label", "n_shingles", "signature")

    def run(batches):
        for tile in by_tile(batches):
            if len({r["label"] for r in tile}) > 1:
                found = candidates(*columns(tile), similar)
                if len(found):
                    chosen = [tile[i] for i in np.unique(found).tolist()]
                    yield pa.RecordBatch.from_pylist([{"grp": r["grp"], "rep": r["rep"], "label": r["label"]} for r in chosen], pa.schema([("grp", pa.struct([("kind", pa.int32()), ("id", pa.int64())])), ("rep", pa.int64()), ("label", pa.int64())]))

    found = tiled(rows, sizes, "n_shingles", "signature").mapInArrow(lean(run), "grp struct<kind:int,id:bigint>, rep long, label long").distinct()
    return found.join(classes.select("rep", "n_shingles", "signature"), "rep")


def within_groups(members: DataFrame, items: DataFrame, similar: int) -> DataFrame:
    """Links between members (grp, rep, label, n_shingles, signature) of one group, confirmed on full sets.

    Every pair of a group's blocks is a tile, which has the full sets of two blocks of bounded bytes and gives links, never
    pairs. However large a group, no task has more.
    """
    per = F.greatest(F.count("*") / SETS_BLOCK, F.sum("n_shingles") * 8 / SETS_BYTES)
    sizes = members.groupBy("grp").agg(F.ceil(per).cast("int").alias("blocks"))
    rows = members.join(items.toDF("rep", "items"), "rep")

    def run(batches):
        for tile in by_tile(batches):
            sig, size, label, block = columns(tile)
            pairs = candidates(sig, size, label, block, similar)
            if len(pairs):
                got = list(tile_links(pairs, [np.frombuffer(r["items"], np.uint64) for r in tile], label, similar))
                if got:
                    ends = [sorted((tile[i]["rep"], tile[j]["rep"])) for i, j in got]
                    yield pa.RecordBatch.from_arrays([pa.array([e[k] for e in ends], pa.int64()) for k in (0, 1)], ["a", "b"])

    return tiled(rows, sizes, "n_shingles", "signature", "items").mapInArrow(lean(run), "a long, b long")


def near_duplicates(docs: DataFrame, size: int = SHINGLE, similar: int = SIMILAR) -> DataFrame:
    """(doc_id, text_key, n_shingles, component_id, kept) for every document; text_key tells rows of one doc_id apart."""
    docs = keyed(docs)
    sets = written(sketches(docs, size), "op7-sets")
    classes = written(sets.where("n_shingles > 0 and doc_id is not null").groupBy("s1", "s2", "n_shingles").agg(F.min("doc_id").alias("rep"), F.min("signature").alias("signature")), "op7-classes")
    keys = indexed(classes, most_different(similar))
    many = keys.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    met = buckets = written(keys.join(many, "key"), "op7-buckets")
    weight = met.groupBy("rep").agg(F.sum("n").alias("weight"))
    met = met.drop("n")
    centre = F.max_by("rep", F.struct("weight", -F.col("rep")))
    first = centres = written(met.join(weight, "rep").groupBy("key").agg(centre.alias("c"), F.max("weight").alias("cw")), "op7-centres")
    group = met.join(first, "key").groupBy("rep").agg(F.max_by("c", F.struct("cw", -F.col("c"))).alias("grp"))
    first = first.drop("cw")
    pairs = met.join(first, "key").where("rep <> c").select(F.least("rep", "c").alias("a"), F.greatest("rep", "c").alias("b")).distinct()
    pairs = written(near(pairs, classes, similar), "op7-0-pairs")
    ids = pairs.select(F.col("a").alias("doc_id")).union(pairs.select(F.col("b").alias("doc_id"))).distinct()
    items = full_sets(docs, ids, size, "op7-0")
    links = confirmed(pairs, items, similar, "op7-0")
    dropped(pairs, items)
    labels = components(links, "op7-0")
    dropped(links)
    marked = met.join(labels.toDF("rep", "component"), "rep", "left").select("key", "rep", F.coalesce("component", "rep").alias("label"))
    open_keys = marked.groupBy("key").agg(F.min("label").alias("low"), F.max("label").alias("high")).where("low < high").select("key")
    left = written(marked.join(open_keys, "key").join(group, "rep"), "op7-open")
    dropped(buckets, centres)
    more = unresolved(left, classes, docs, size, similar)
    dropped(left)
    found = classes.join(labels.toDF("rep", "component"), "rep", "left").select("s1", "s2", "n_shingles", "rep", F.coalesce("component", "rep").alias("label"))
    upper = None
    if not more.isEmpty():  # these links are between components: only their labels are joined anew
        ends = found.select("rep", "label")
        upper = components(more.join(ends.toDF("a", "x"), "a").join(ends.toDF("b", "y"), "b").select(F.col("x").alias("a"), F.col("y").alias("b")), "op7-1")
        found = found.join(upper.toDF("label", "component"), "label", "left").select("s1", "s2", "n_shingles", F.coalesce("component", "label").alias("label"))
    joined = written(found.select("s1", "s2", "n_shingles", F.col("label").alias("component")), "op7-labels")
    dropped(classes, labels, more, upper)
    return sets.join(joined, ["s1", "s2", "n_shingles"], "left").select("doc_id", "text_key", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"), F.coalesce(F.coalesce("component", "doc_id") == F.col("doc_id"), F.lit(True)).alias("kept"))
