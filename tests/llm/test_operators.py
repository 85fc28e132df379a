"""The operators against plain Python, on the small tables and on rows made to be awkward."""

import gzip
import glob
import html
import random
import re
from collections import Counter, defaultdict

import brute
import numpy as np
import pytest
from pyspark.sql import functions as F

from tempcorr.llm import op1_html, op2_packing, op3_suffix, op4_substring, op5_warc, op6_quality, op7_neardup, op8_scoring, op9_decontamination, op10_language
from tempcorr.llm.automaton import SuffixAutomaton
from tempcorr.llm.components import components
from tempcorr.llm.induced import suffix_array
from tempcorr.llm.queries import queries

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, anchor string, spans int, low int, key int"


def awkward():
    rng = random.Random(5)
    words = ["w%d" % i for i in range(3000)]
    passage = " ".join(rng.choices(words, k=150))
    line = " ".join(rng.choices(words, k=20))
    rows = [(0, None, "en", "a"), (1, "", "en", None), (2, " \n\t ", None, "a"), (3, "one", "en", "b"), (4, "One", "en", "b"), (5, "One two", "en", "b")]
    rows += [(10 + i, passage, "en", "a") for i in range(30)]
    rows += [(100 + i, " ".join(rng.choices(words, k=40)) + " " + passage + " " + " ".join(rng.choices(words, k=40)), "en", "c") for i in range(30)]
    rows += [(200 + i, " ".join(rng.choices(words, k=rng.randint(0, 30))) + "\n" + line + "\n" + " ".join(rng.choices(words, k=30)), "de", "hot") for i in range(60)]
    base = rng.choices(words, k=120)
    for i in range(40):  # copies of one text with one word changed, at different places
        w = list(base)
        w[i * 3] = "x%d" % i
        rows.append((300 + i, " ".join(w), "en", "hot"))
    rows += [(400, "a" * 5000, "en", "a"), (401, "ab" * 3000, "en", "a"), (402, "same " * 2000, "en", "a"), (403, "Ünïcode ß " + passage.replace("w", "ü"), "de", "a"), (404, passage.upper(), "en", "a")]
    rows += [(500, " ".join(rng.choices(words, k=60_000)) + " " + passage, "en", "a")]
    rows += [(501, passage[:700] + " " + passage[100:], "en", "a")]
    return [(*r, len(r[1] or ""), "x", 1, 2, 3) for r in rows]


@pytest.fixture(scope="module")
def rows():
    return awkward()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(5)


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


def got(df, *columns):
    return sorted(tuple(r) for r in df.select(*columns).collect())


SUFFIX = ("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
SUBSTRING = ("doc_id", "n_words", "n_removed", "kept_sha256")
NEAR = ("doc_id", "n_shingles", "component_id", "kept")
HIT = ("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def pairs(rows):
    return [(r[0], r[1]) for r in rows]


def test_suffix_array_against_sorting():
    rng = np.random.default_rng(0)
    for n, a in ((0, 2), (1, 2), (2, 1), (200, 2), (300, 1), (500, 4), (1000, 256)):
        for _ in range(5):
            t = rng.integers(0, a, n).astype(np.int32)
            sa = suffix_array(t, 257, most=64)  # so small a memory that the queues go to disk
            b = t.tolist()
            assert sa[sa < n].tolist() == sorted(range(n), key=lambda i, b=b: b[i:])


def test_suffix_dedup_awkward(docs, rows):
    assert got(op3_suffix.dedup(docs), *SUFFIX) == brute.suffix(pairs(rows))


def test_suffix_dedup_of_rows_with_one_id(spark):
    rng = random.Random(4)
    one, two = ("".join(rng.choices("abcdefgh ", k=1500)) for _ in range(2))
    rows = [(7, one), (7, two), (7, two[:300] + one[:600]), (8, one[100:900]), (9, two), (9, two), (None, two)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted((tuple(r) for r in op3_suffix.dedup(docs).select(*SUFFIX).collect()), key=str) == sorted(_suffix(rows), key=str)


def _suffix(rows):
    """brute.suffix by place: rows of one id, and without an id."""
    return [(rows[i][0], *r[1:]) for i, r in enumerate(brute.suffix([(i, t) for i, (_, t) in enumerate(rows)]))]


def test_suffix_dedup_table(spark, small):
    table = spark.read.parquet(f"{small}/documents.parquet")
    assert got(queries()["op3_suffix_dedup"](spark, small), *SUFFIX) == brute.suffix([tuple(r) for r in table.select("doc_id", "text").collect()])


def test_suffix_dedup_of_planted_passages(spark):
    """Passages of 51 to 80 words in other texts: those of 400 bytes with the spaces around are removed whole, of a shorter one no byte is."""
    rng = random.Random(23)
    word = lambda: "".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=rng.randint(2, 9)))
    rows, size = [], {}
    for i in range(60):
        passage = f" {' '.join(word() for _ in range(rng.randint(51, 80)))} "
        for j in range(2):
            size[2 * i + j] = len(passage)
            rows.append((2 * i + j, " ".join(word() for _ in range(150)) + f" {i}.{j}{passage}{j}.{i} " + " ".join(word() for _ in range(150))))
    rows += [(1000 + i, " ".join(word() for _ in range(300))) for i in range(60)]
    found = {r["doc_id"]: r for r in op3_suffix.dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert 20 < sum(n < 400 for n in size.values()) < 100
    for d, r in found.items():
        assert (r["n_removed"] >= size[d]) if size.get(d, 0) >= 400 else r["n_removed"] == 0
    assert [tuple(found[d][c] for c in SUFFIX) for d in sorted(found)] == brute.suffix(rows)


def test_suffix_dedup_hot_anchors(spark, docs, rows, monkeypatch):
    from tempcorr.llm import anchors

    real = anchors.hot_anchors
    monkeypatch.setattr(anchors, "hot_anchors", lambda d, make, w, k, most: anchors.table_of(d, make, w, k).groupBy("anchor").count().where("count > 5").select("anchor"))
    assert got(op3_suffix.dedup(docs), *SUFFIX) == brute.suffix(pairs(rows))
    assert got(op4_substring.dedup(docs), *SUBSTRING) == brute.substring(pairs(rows))
    assert real is not anchors.hot_anchors


def test_substring_dedup_awkward(docs, rows):
    assert got(op4_substring.dedup(docs), *SUBSTRING) == brute.substring(pairs(rows))


def test_substring_dedup_table(spark, small):
    table = spark.read.parquet(f"{small}/documents.parquet")
    assert got(queries()["op4_substring_dedup"](spark, small), *SUBSTRING) == brute.substring([tuple(r) for r in table.select("doc_id", "text").collect()])


def test_automaton_gets_matching_stretches_once(monkeypatch):
    """Of strings of 60 words the automaton gets the stretch that others have, once; the spans are those of a plain count."""
    got = []

    class Counted(op4_substring.SuffixAutomaton):
        def add(self, tokens, owner):
            tokens = list(tokens)
            got.append(len(tokens))
            super().add(tokens, owner)

    monkeypatch.setattr(op4_substring, "SuffixAutomaton", Counted)
    rng = random.Random(18)
    shared = [f"s{i}" for i in range(16)]
    rows = []
    for anchor in (5, 6):
        for doc in (7, 3, 9, 9, 20):
            own = [f"{anchor}w{rng.randint(0, 10**6)}" for _ in range(44)]
            cut = rng.randint(0, 44)
            words = own[:cut] + [f"{anchor}{x}" for x in shared] + own[cut:]
            rows.append({"anchor": anchor, "doc_id": doc, "start": 100 * doc, "windows": 48, "content": " ".join(words).encode(), "cut": cut})
    rows.append({"anchor": 8, "doc_id": 1, "start": 0, "windows": 1, "content": b" ".join(b"x%d" % i for i in range(13)), "cut": 0})
    found = sorted(op4_substring.earlier(13)(rows))
    assert found == sorted((r["doc_id"], r["start"] + r["cut"], r["start"] + r["cut"] + 16) for r in rows if r["doc_id"] > 3)
    assert got == [16, 16]


def test_automaton_statistics():
    rng = random.Random(1)
    texts = [[rng.choice("abc") for _ in range(rng.randint(0, 40))] for _ in range(12)]
    machine = SuffixAutomaton()
    for i, t in enumerate(texts):
        machine.add(t, i)
    machine.finish()
    for t in [*texts, [rng.choice("abcd") for _ in range(60)]]:
        for end, owner in enumerate(machine.statistics(t, 4)):
            part = t[max(0, end - 3) : end + 1]
            want = min((i for i, x in enumerate(texts) if len(part) == 4 and any(x[j : j + 4] == part for j in range(len(x)))), default=None)
            assert owner == want


def test_near_duplicates_awkward(docs, rows):
    assert got(op7_neardup.near_duplicates(docs), *NEAR) == brute.neardup(pairs(rows))


def test_near_duplicates_table(spark, small):
    table = spark.read.parquet(f"{small}/documents.parquet")
    assert got(queries()["op7_neardup"](spark, small), *NEAR) == brute.neardup([tuple(r) for r in table.select("doc_id", "text").collect()])


def test_full_sets_shuffle_only_the_texts_they_need(spark):
    """Of 3,000 documents the sets of 200 are made; all of these pass the filter, also a full one, and few others do."""
    rng = random.Random(19)
    docs = spark.createDataFrame([(i * 7 - 900, f"a{i} b c d{i % 5} e") for i in range(3000)] + [(None, "no id"), (-900, "again")], "doc_id long, text string")
    chosen = sorted(rng.sample(range(3000), 200))
    ids = spark.createDataFrame([(i * 7 - 900,) for i in chosen], "doc_id long")
    found = {r["doc_id"]: bytes(r["items"]) for r in op7_neardup.full_sets(docs, ids, 3, "test").collect()}
    assert sorted(found) == [i * 7 - 900 for i in chosen]
    assert all(found[i * 7 - 900] == op7_neardup.shingles(f"a{i} b c d{i % 5} e".encode()).tobytes() for i in chosen if i)
    through = {r["doc_id"] for r in op7_neardup.passed(docs, ids).collect()}
    assert set(found) <= through and len(through) < 230
    words, own = np.full(1, 2**64 - 1, np.uint64), np.array(chosen, np.int64)
    assert op7_neardup.passing(own, words).all() and not op7_neardup.passing(own, words * np.uint64(0)).any()
    assert op7_neardup.passed(docs, ids.where("false")).count() == 0


def test_near_duplicates_of_another_similarity(spark):
    """Chains of texts cut by 15 to 20 percent: their sizes stand at 80 to 85 percent, and neighbours have different centres."""
    rng = random.Random(9)
    rows = []
    for c in range(20):
        words, n, i = ["c%dw%d" % (c, rng.randint(0, 10**9)) for _ in range(1200)], 1200, 0
        while n > 60:
            rows.append((100 * c + i, " ".join(words[:n])))
            i, n = i + 1, int((n - 4) * rng.uniform(0.805, 0.845)) + 5
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert got(op7_neardup.near_duplicates(docs, 5, 80), *NEAR) == brute.neardup(rows, 5, 80)


def test_index_finds_all_under_the_distance():
    rng = np.random.default_rng(2)
    for _ in range(300):
        a = rng.integers(0, 65536, 64).astype(np.uint16)
        b = a.copy()
        at = rng.choice(64, op7_neardup.MOST_DIFFERENT, replace=False)
        b[at] ^= 1
        keys = []
        import pyarrow as pa

        for s in (a, b):
            for out in _keys(pa, s):
                keys.append(out)
        assert set(keys[0]) & set(keys[1])


def _keys(pa, s):
    class Frame:
        def select(self, *a):
            return self

        def mapInArrow(self, f, schema):
            batch = pa.RecordBatch.from_arrays([pa.array([1]), pa.array([s.tobytes()])], ["rep", "signature"])
            return [next(f(iter([batch]))).column(0).to_pylist()]

    return op7_neardup.indexed(Frame())


def test_components_of_chains(spark):
    links = [(i, i + 1) for i in range(60)] + [(100, 200), (200, 150), (7, 7)]
    found = {r["id"]: r["component"] for r in components(spark.createDataFrame(links, "a long, b long"), "t").collect()}
    assert found == {**{i: 0 for i in range(61)}, 100: 100, 150: 100, 200: 100}


def test_decontamination(spark, docs, rows):
    items = [(0, rows[20][1][:400]), (1, "w1 w2"), (2, None), (3, ""), (4, "same"), (4, "same"), (5, " ".join(rows[20][1].split()[5:18])), (6, "absent words only here")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = brute.decontamination(pairs(rows), items)
    assert got(op9_decontamination.judge(op9_decontamination.find(docs, bench)), *HIT) == want
    assert got(op9_decontamination.judge(op9_decontamination.find(docs, bench, most_bytes=300)), *HIT) == want
    twice = docs.where("doc_id in (3, 10, 402)").unionByName(docs).unionByName(docs.where("doc_id = 3").withColumn("text", F.lit("w1 w2 w1 w2")))
    few, many = (got(op9_decontamination.judge(op9_decontamination.find(twice, bench, most_bytes=n)), *HIT) for n in (1 << 20, 300))
    assert few == many and len(few) == len(rows) + 4
    assert op9_decontamination.clean(twice, bench).where("doc_id = 3").count() == 2  # the third row of this id is contaminated
    none = bench.limit(0)
    assert all(not r["contaminated"] for r in op9_decontamination.judge(op9_decontamination.find(docs, none)).collect())


def test_decontamination_table(spark, middle):
    table, bench = (spark.read.parquet(f"{middle}/{t}.parquet") for t in ("documents", "benchmark"))
    want = brute.decontamination([tuple(r) for r in table.select("doc_id", "text").collect()], [tuple(r) for r in bench.select("item_id", "text").collect()])
    assert got(queries()["op9_decontamination"](spark, middle), *HIT) == want


def test_quality(spark, docs, rows, middle):
    base = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
    assert got(op6_quality.clean(docs), *base) == brute.quality(pairs(rows))
    table = spark.read.parquet(f"{middle}/documents.parquet")
    assert got(queries()["op6_quality"](spark, middle), *base) == brute.quality([tuple(r) for r in table.select("doc_id", "text").collect()])
    plan = op6_quality.clean(table)._jdf.queryExecution().toString()
    assert "Exchange" not in plan and "Python" not in plan and "Arrow" not in plan


def test_quality_verdicts(spark):
    prose = "The quick brown fox jumps over the lazy dog and then goes home.\n" * 1
    lines = [f"On day {i} the {a} went to the {b} and {c} all of it." for i, (a, b, c) in enumerate([("baker", "mill", "bought"), ("farmer", "market", "sold"), ("sailor", "harbour", "drank"), ("writer", "study", "wrote"), ("judge", "court", "heard"), ("child", "garden", "ate")])]
    cases = [(1, "\n".join(lines), True), (2, "Home | About | Contact | Blog | Help | Login | More\n" * 9, False), (3, prose, False), (4, "\n".join([*lines, "All rights reserved.", "Home"]), True)]
    found = {r["doc_id"]: r for r in op6_quality.clean(spark.createDataFrame([c[:2] for c in cases], "doc_id long, text string")).collect()}
    assert {k: r["kept"] for k, r in found.items()} == {c[0]: c[2] for c in cases}
    assert found[4]["kept_text"] == "\n".join(lines)


def test_quality_phrases_are_words(spark):
    lines = ["The catalog in the hall is old.", "He worked on design in Paris.", "A backlog in the office grew.", "Please log in here.", "Sign up now!", "We read more books than they did, and on every evening of that long winter we talked about what was in them."]
    r = op6_quality.clean(spark.createDataFrame([(1, "\n".join(lines))], "doc_id long, text string")).first()
    assert r["kept_text"].split("\n") == [lines[i] for i in (0, 1, 2, 5)] and r["kept"]


def test_packing(spark, docs, rows, small):
    from public_tokenizers import path
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path("byte_bpe_50k.json"))
    special = [(9001, "one <|endoftext|> two<|endoftext|><|endoftext|>", "en", "a", 0, "x", 1, 2, 3), (9002, "<|endoftext|>", "en", "a", 0, "x", 1, 2, 3), (9003, "<|endoftext| >", "en", "b", 0, "x", 1, 2, 3)]
    docs, rows = docs.unionByName(spark.createDataFrame(special, SCHEMA)), [*rows, *special]
    table = [tuple(r) for r in spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").collect()]
    for df, source in ((op2_packing.pack(docs), pairs(rows)), (queries()["op2_packing"](spark, small), table), (op2_packing.pack(docs, 256, {"hot": 3, "a": 1, "c": 1}), pairs(rows))):
        window = 256 if df is None else 2048
        found = df.collect()
        window = max(r["offset"] + r["length"] for r in found)
        ids = {d: [*t.encode(x or "", add_special_tokens=False).ids, 1] for d, x in source}
        by = defaultdict(list)
        for r in found:
            by[r["doc_id"]].append(r)
            part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
            assert r["ids_crc32"] == brute.crc(part) and r["doc_tokens"] == len(ids[r["doc_id"]]) and r["length"] > 0
        assert set(by) == set(ids)
        for d, pieces in by.items():
            at = 0
            for r in sorted(pieces, key=lambda r: r["start"]):
                assert r["start"] == at
                at += r["length"]
            assert at == len(ids[d])
        sequences = defaultdict(list)
        for r in found:
            sequences[r["sequence_id"]].append(r)
        total = sum(map(len, ids.values()))
        assert len(sequences) == -(-total // window)
        for s, pieces in sequences.items():
            at = 0
            for r in sorted(pieces, key=lambda r: r["offset"]):
                assert r["offset"] == at
                at += r["length"]
            assert at == window or s == max(sequences)


def test_packing_keeps_the_mixture(spark, small):
    found = queries()["op2_packing"](spark, small).collect()
    total, by = Counter(), defaultdict(Counter)
    for r in found:
        total[r["source"]] += r["length"]
        by[r["sequence_id"]][r["source"]] += r["length"]
    n = sum(total.values())
    for s, own in by.items():
        if s < max(by):
            for source, k in total.items():
                assert abs(own[source] - 2048 * k / n) <= 2


def test_packing_serves_every_source(spark):
    """A target for a small source beyond the 63 largest is kept from the first window on."""
    rows = [(100 * s + i, "word " * (200 - s), "s%d" % s) for s in range(100) for i in range(3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    found = op2_packing.pack(docs, 64, {"s0": 1, "s95": 1}).where("sequence_id = 0").groupBy("source").agg(F.sum("length").alias("n")).collect()
    assert {r["source"]: r["n"] for r in found} == {"s0": 32, "s95": 32}


def test_encoder_is_the_tokenizer():
    from public_tokenizers import path
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path("byte_bpe_50k.json"))
    t.encode_special_tokens = True
    encode = op2_packing.Encoder()
    rng = random.Random(3)
    parts = ["word", "Ünï", " ", "  ", "\n", "\t", "it's", "'s", "12", ".", "...", "<|endoftext|>", " ", "漢字", "😀", "\x00", "\r\n", "don't", "--", "é", " ", "\x1f"]
    for _ in range(3000):
        text = "".join(rng.choices(parts, k=rng.randint(0, 12)))
        assert np.frombuffer(encode(text), np.uint16).tolist() == t.encode(text, add_special_tokens=False).ids, repr(text)


def test_encoder_of_special_tokens():
    """Both ways that the library has: a special token in a text is that token, or, with encode_special_tokens, text."""
    from public_tokenizers import path
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path("byte_bpe_50k.json"))
    rng = random.Random(4)
    parts = ["word", "Ünï", " ", "  ", "\n", "'s", "12", "<|endoftext|>", "<|endoftext|", "endoftext|>", "<|", "|>", "漢字", "\x00", "é", "\u00a0"]
    texts = ["".join(rng.choices(parts, k=rng.randint(0, 12))) for _ in range(2000)] + ["<|endoftext|>", "a<|endoftext|><|endoftext|> b"]
    for special in (True, False):
        t.encode_special_tokens = not special
        encode = op2_packing.Encoder(special=special)
        for text in texts:
            assert np.frombuffer(encode(text), np.uint16).tolist() == t.encode(text, add_special_tokens=False).ids, repr(text)


def test_warc(spark, tmp_path):
    big = "<p>é" + "x" * 2000
    rows = [(1, "http://a.example.com/x", big), (2, "http://b.example.com/", big), (3, None, None), (4, "http://a.example.com/x y\r\n", "short"), (5, "http://a.example.com/z", "short"), (6, "http://a.example.com/x", big), (7, "http://c.example.org", "line\r\n\r\nWARC/1.1\r\n\r\n" + "y" * 1500), (8, "", "")]
    pages = spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, digest string")
    df = op5_warc.archive(pages, str(tmp_path / "w"))
    assert sorted(tuple(r) for r in df.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to").collect()) == brute.warc([(r[0], r[2]) for r in rows])
    order = [(r["urlkey"], r["captured"], r["page_id"]) for r in df.collect()]
    assert order == sorted(order)
    raw = b"".join(gzip.open(f).read() for f in glob.glob(f"{tmp_path}/w/*.gz"))
    assert len(list(op5_warc.parse(raw))) == len(rows)


def test_warc_of_repeated_and_missing_ids(spark, tmp_path):
    p, q, r = ("<p>" + c * 1500 for c in "pqr")
    rows = [(5, p), (5, q), (9, p), (9, r), (3, r), (None, r), (None, None)]
    df = op5_warc.archive(spark.createDataFrame([(i, "http://h.org/", h) for i, h in rows], "page_id long, url string, html string"), str(tmp_path / "w"))
    found = [(r["page_id"], r["record_type"], r["refers_to"]) for r in df.collect()]
    want = [(5, "revisit", 9), (5, "response", None), (9, "response", None), (9, "response", None), (3, "revisit", 9), (None, "revisit", 9), (None, "response", None)]
    assert Counter(found) == Counter(want)


def test_runs_are_merged_from_disk_in_passes(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(op5_warc, "FAN", 3)
    rng, schema = random.Random(2), pa.schema([("a", pa.string()), ("b", pa.string()), ("c", pa.int64())])
    runs = [sorted((rng.choice("abc"), rng.choice("xy"), rng.randint(0, 99)) for _ in range(rng.randint(1, 400))) for _ in range(20)]
    file = op5_warc.RunFile(schema)
    for rows in runs:
        file.runs.append([])
        file.add(file._batch(rows))
    found = [tuple(r.values()) for b in file.merged() for r in b.to_pylist()]
    assert found == sorted(x for r in runs for x in r)


def test_warc_table(spark, small):
    table = spark.read.parquet(f"{small}/pages.parquet").select("page_id", "html").collect()
    df = queries()["op5_warc"](spark, small).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
    assert sorted(tuple(r) for r in df.collect()) == brute.warc([tuple(r) for r in table])


def test_loser_tree():
    rng = random.Random(4)
    for k in (0, 1, 2, 3, 7, 16):
        runs = [sorted(rng.randint(0, 50) for _ in range(rng.randint(0, 20))) for _ in range(k)]
        assert list(op5_warc.LoserTree(runs, lambda x: x)) == sorted(x for r in runs for x in r)


def article(page):
    """What the pages of the tables declare as their article."""
    inner = re.search(r"<article>(.*?)</article>", page, re.S)[1]
    out = [re.sub(r"\s+", " ", html.unescape(re.sub(r"</?(b|br)>", " " if "br" in b else "", b) if False else re.sub(r"<[^>]*>", lambda m: " " if "br" in m[0] else "", b))).strip() for b in re.split(r"</?(?:p|h1)>", inner)]
    return "\n\n".join(b for b in out if b)


def test_html_table(spark, middle):
    table = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{middle}/pages.parquet").collect()}
    for r in queries()["op1_html_extraction"](spark, middle).collect():
        assert r["text"] == article(table[r["page_id"]]) and r["n_chars"] == len(r["text"])


def test_html_cases():
    def text(page):
        return "\n\n".join(t for t, _ in op1_html.blocks(page))

    assert text("<body><nav>Menu <b>x</b></nav><main><p>One &amp; two<p>Three <i>f</i>our</main><footer>f</footer>") == "One & two\n\nThree four"
    assert text('<div class="cookie-notice">c<div>d</div></div><div>keep<br>this</div><script>var a="<p>no</p>";</script><style>p{}</style>') == "keep this"
    assert text('<article><p>Body</p><section id="comments"><p>Nice</p></section></article><form><input>q</form>') == "Body"
    assert text("<p>a &lt;b&gt; &#233;&nbsp;c\n\t d</p><!-- <p>x</p> --><p>2 < 3</p>") == "a <b> é c d\n\n2 < 3"
    assert text('<p class="ad">advert<p>text</p>') == "text"
    assert text("") == "" and text("plain") == "plain"
    assert text("<p>a</p><script>never closed") == "a"


def test_html_boilerplate_of_a_host(spark):
    same = "Contact our friendly team by phone or by mail at any hour of the day"
    rng = random.Random(6)
    rows = []
    for i in range(20):
        body = " ".join(f"t{rng.randint(0, 5000)}" for _ in range(80))
        rows.append((i, "http://h.example.com/%d" % i, f"<body><div>{same}</div><p>{body}</p></body>", 7))
    rows += [(100, None, None, 7), (101, "x", "", 7), (102, "http://h.example.com/a", "<body><article><p>" + same + "</p></article></body>", 7)]
    found = {r["page_id"]: r["text"] for r in op1_html.extract(spark.createDataFrame(rows, "page_id long, url string, html string, host int")).collect()}
    assert len(found) == 23 and found[100] == "" and found[101] == "" and found[102] == same
    assert all(same not in found[i] and found[i].startswith("t") for i in range(20))


def test_html_runs_count_over_a_whole_host(spark):
    """A run on three pages of a host of 1,500 is found, wherever the pages lie; a run on two is not, nor one that only two hosts together have thrice."""
    rng = random.Random(16)
    words = lambda name, n: " ".join(f"{name}{i}" for i in range(n))
    thrice, twice, hosts = words("three", 12), words("two", 12), words("host", 12)
    extra = {3: thrice, 700: thrice, 1400: thrice, 11: twice, 900: twice, 5: hosts, 1001: hosts}
    rows = []
    for i in range(1500):
        body = " ".join(f"t{rng.randint(0, 10**6)}" for _ in range(30))
        rows.append((i, f"http://h.example.com/{i}", f"<div>{extra.get(i, words(f'own{i}_', 12))}</div><p>{body}</p>"))
    rows.append((1500, "http://g.example.com/a", f"<div>{hosts}</div><p>{words('other', 30)}</p>"))
    found = {r["page_id"]: r for r in op1_html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert len(found) == 1501
    for i, r in found.items():
        assert r["n_removed_blocks"] == (1 if i in (3, 700, 1400) else 0), i
    assert all(thrice not in found[i]["text"] for i in (3, 700, 1400)) and all(extra[i] in found[i]["text"] for i in (11, 900, 5, 1001))


def test_html_shared_runs_against_counting(spark, monkeypatch):
    """The blocks that stay are those that a count of all runs of a host gives, with hot runs and a small memory of a task."""
    monkeypatch.setattr(op1_html, "SENT", 50, raising=False)
    rng = random.Random(17)
    lines = [" ".join(rng.choices("abcdefgh", k=rng.randint(3, 30))) for _ in range(60)]
    pages = [[rng.choice(lines) if rng.random() < 0.3 else " ".join(f"{rng.choice('ab')}{rng.randint(0, 400)}" for _ in range(rng.randint(1, 30))) for _ in range(rng.randint(1, 8))] for _ in range(900)]
    rows = [(i, f"http://{'a' if i % 3 else 'b'}/{i}", "".join(f"<p>{x}</p>" for x in p)) for i, p in enumerate(pages)]
    seen = {}
    for i, p in enumerate(pages):
        w = " ".join(p).split()
        for j in range(len(w) - 7):
            seen.setdefault((i % 3 > 0, tuple(w[j : j + 8])), set()).add(i)
    expected = {}
    for i, p in enumerate(pages):
        w, sizes = " ".join(p).split(), [len(x.split()) for x in p]
        hit = [False] * len(w)
        for j in range(len(w) - 7):
            if len(seen[i % 3 > 0, tuple(w[j : j + 8])]) >= 3:
                hit[j : j + 8] = [True] * 8
        at = [sum(sizes[:k]) for k in range(len(p) + 1)]
        copy = 2 * sum(hit) > len(w)
        expected[i] = "\n\n".join(x for k, x in enumerate(p) if copy or sum(hit[at[k] : at[k + 1]]) < 0.6 * sizes[k])
    found = {r["page_id"]: r["text"] for r in op1_html.extract(spark.createDataFrame(rows, "page_id long, url string, html string").repartition(13)).collect()}
    assert found == expected and sum(found[i] != "\n\n".join(p) for i, p in enumerate(pages)) > 50


def test_language(spark, docs, middle):
    table = spark.read.parquet(f"{middle}/documents.parquet")
    df = queries()["op10_language"](spark, middle).join(table.select("doc_id", "lang", "text"), "doc_id").where("held_out and length(text) > 60").collect()
    assert sum(r["lang_pred"] == r["lang"] for r in df) > 0.97 * len(df)
    found = {r["doc_id"]: r for r in op10_language.identify(docs).collect()}
    assert len(found) == docs.count() and all(found[i]["lang_pred"] == "und" and found[i]["score"] == 0 for i in (0, 1, 2))
    assert all(0 <= r["score"] <= 1 for r in found.values())
    assert all(r["lang_pred"] == "und" for r in op10_language.identify(docs.withColumn("lang", F.lit(None).cast("string"))).collect())


def test_language_rejects_by_calibration(spark, middle):
    table = spark.read.parquet(f"{middle}/documents.parquet")
    rng = random.Random(8)
    noise = spark.createDataFrame([(10**6 + i, "".join(rng.choices("qxzjkwvy bfg", k=400))) for i in range(30)], "doc_id long, text string")
    docs = table.unionByName(noise, allowMissingColumns=True)
    kept = {r["doc_id"] for r in op10_language.accepted(docs).select("doc_id").collect()}
    assert not any(i >= 10**6 for i in kept)
    prose = [r["doc_id"] for r in table.where("length(text) > 300").select("doc_id").collect()]
    assert len(kept.intersection(prose)) >= 0.98 * len(prose)


def test_language_of_large_scripts(spark):
    """Two rare scripts beside a large one are told apart, and what has no letter has no language."""
    rng = random.Random(10)
    large, one, two = [chr(0x4E00 + i) for i in range(3000)], [chr(0x10D0 + i) for i in range(33)], [chr(0x0561 + i) for i in range(38)]
    make = lambda letters, words: " ".join("".join(rng.choices(letters, k=5)) for _ in range(words))
    rows = [(i, make(large, 200), "zh") for i in range(100)] + [(200 + i, make(one, 30), "ka") for i in range(20)] + [(300 + i, make(two, 30), "hy") for i in range(20)]
    rows += [(400, "\U0001f600 \U0001f601\U0001f602", None), (401, "\u3001\u3002\u300c\u300d", None), (402, "\uff11\uff12\uff13", None)]
    found = {r["doc_id"]: r for r in op10_language.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert all(found[i]["lang_pred"] == (lang or "und") for i, _, lang in rows)
    assert all(found[i]["score"] == 0 for i in (400, 401, 402))


def test_kneser_ney_sums_to_one():
    rng = np.random.default_rng(0)
    s = rng.integers(0, 6, 400).astype(np.uint8)
    k, n = np.unique(op10_language.grams(s, 4), return_counts=True)
    m = op10_language.KneserNey(dict(zip(k.tolist(), n.tolist())))
    for context in (0x000102, 0x030303, 0x090909):
        p = m.probability(np.arange(256, dtype=np.uint32) | np.uint32(context << 8), 4)
        assert abs(p.sum() - 1) < 1e-9


def test_scoring(spark, docs, small):
    df = op8_scoring.score(docs)
    found = {r["doc_id"]: r for r in df.collect()}
    assert found[0]["n_tokens"] == 0 and found[0]["log_prob"] == 0 and found[0]["mean_log_prob"] is None
    assert all(r["log_prob"] < 0 for r in found.values() if r["n_tokens"])
    parts = [sorted((r["doc_id"], r["log_prob"]) for r in op8_scoring.score(docs.repartition(n)).collect()) for n in (1, 7)]
    assert all(a[0] == b[0] and abs(a[1] - b[1]) < 1e-6 * max(1, abs(a[1])) for a, b in zip(*parts, strict=True))


def test_scoring_prefers_real_order(spark, middle):
    """A text with its words in another order is less likely: by the ids of the network that the whole table has trained."""
    from tempcorr.llm.common import keyed

    docs = spark.read.parquet(f"{middle}/documents.parquet")
    _, _, table, net = op8_scoring.fitted(keyed(docs))
    rng, better = random.Random(0), []

    def total(words):
        ids = op8_scoring.framed(" ".join(words).encode(), table)
        at = np.arange(op8_scoring.SIDE, len(ids) - op8_scoring.SIDE)
        return net.log_probs(op8_scoring.around(ids, at), ids[at]).sum()

    for r in docs.where("length(text) > 1500").limit(150).collect():
        words = r["text"].split()
        better.append(total(words) > total(rng.sample(words, len(words))))
    assert len(better) > 100 and np.mean(better) > 0.85, np.mean(better)


def test_scoring_gradient():
    rng = np.random.default_rng(0)
    net = op8_scoring.Network()
    context, target = rng.integers(0, 1024, (64, 4)), rng.integers(0, 1024, 64)
    before = net.log_probs(context, target).sum()
    memory = np.zeros(len(net.flat), np.float32)
    for _ in range(30):
        net.train(context, target, memory)
    assert net.log_probs(context, target).sum() > before
    total = sum(np.exp(net.log_probs(context[:1], np.array([w])))[0] for w in range(1024))
    assert abs(total - 1) < 1e-4


def test_scoring_knows_every_word(spark):
    """The probabilities of all words in one place add up to no more than one, however many words share an id."""
    rng = random.Random(8)
    words = ["r%d" % i for i in range(6000)]
    rows = [(i, w) for i, w in enumerate(words)] + [(10_000 + i, " ".join(rng.choices(words[:2000], k=100) + ["the"] * 150)) for i in range(100)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    counts = op8_scoring.word_counts(docs)
    assert counts.count() == 6001 and counts.agg(F.sum("n")).first()[0] == 6000 + 25_000
    table = op8_scoring.vocabulary(counts, 0.7)
    assert 100 < table.own < 2001 < table.classes**2 * 2 and op8_scoring.vocabulary(counts, 0.8).own > table.own
    found = {r["doc_id"]: r["log_prob"] for r in op8_scoring.score(docs).where("doc_id < 10000").collect()}
    assert len(found) == 6000 and 0.5 < sum(np.exp(v) for v in found.values()) < 1.0001
    twice = docs.unionByName(docs.where("doc_id = 10001"))
    same = [r["log_prob"] for r in op8_scoring.score(twice).where("doc_id = 10001").collect()]
    assert len(same) == 2 and same[0] == pytest.approx(same[1], rel=1e-7) and same[0] < 0


def test_scoring_trains_on_every_word(spark):
    """The words of short texts are learnt whatever their doc_id."""
    for doc in range(4):
        docs = spark.createDataFrame([(4 * i + doc, "alpha") for i in range(200)], "doc_id long, text string")
        table = op8_scoring.vocabulary(op8_scoring.word_counts(docs))
        untrained = op8_scoring.Network(classes=table.classes)
        ids = op8_scoring.framed(b"alpha", table)
        at = np.array([op8_scoring.SIDE])
        before = untrained.log_probs(op8_scoring.around(ids, at), ids[at])[0]
        assert op8_scoring.score(docs).first()["log_prob"] > before + 0.1


def test_empty_tables(spark, nothing):
    bench = spark.createDataFrame([], "item_id long, text string")
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    for df in (op1_html.extract(pages), op2_packing.pack(nothing), op3_suffix.dedup(nothing), op4_substring.dedup(nothing), op5_warc.archive(pages), op6_quality.clean(nothing), op7_neardup.near_duplicates(nothing), op8_scoring.score(nothing), op9_decontamination.judge(op9_decontamination.find(nothing, bench)), op10_language.identify(nothing)):
        assert df.count() == 0


def test_repeated_rows(spark, docs):
    twice = docs.where("doc_id in (10, 403, 3, 500)").unionByName(docs.where("doc_id in (10, 403, 3, 500)"))
    assert op3_suffix.dedup(twice).where("doc_id = 500").agg(F.min("n_removed") == F.min("n_bytes")).first()[0]
    assert op4_substring.dedup(twice).count() == 8
    assert op7_neardup.near_duplicates(twice).where("kept").count() == 8
    assert op6_quality.clean(twice).count() == 8 and op8_scoring.score(twice).count() == 8
