"""The correlation engine: estimator truths, incremental states, searches, operators, streams, plans."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from tempcorr import evaluate, sql
from tempcorr.functions import kernel as K
from tempcorr.functions import measures as M
from tempcorr.operators import panes, prep
from tempcorr.operators import windows as W
from tempcorr.plans import search
from tempcorr.sources import synth, tables
from tempcorr.streaming import live


def gauss(rho, n=500, seed=0):
    rng = np.random.default_rng(seed)
    x = rng.standard_normal(n)
    return x, rho * x + (1 - rho * rho) ** 0.5 * rng.standard_normal(n)


@pytest.mark.parametrize("rho", [0.0, 0.5, 0.9])
def test_gaussian_truth(rho):
    got = np.mean([K.knn_mi(*gauss(rho, seed=s)) for s in range(5)])
    assert abs(got + 0.5 * np.log(1 - rho * rho)) < 0.08
    assert abs(np.mean([K.knn_mi(*gauss(rho, seed=s), variant=1) for s in range(5)]) + 0.5 * np.log(1 - rho * rho)) < 0.08


def test_literal_extent_is_biased():
    assert np.mean([K.knn_mi(*gauss(0, seed=s), extent="kth") for s in range(3)]) > 0.5


def test_estimator_properties():
    x, y = gauss(0.7)
    assert K.knn_mi(x, y) == pytest.approx(K.knn_mi(y, x))
    assert K.knn_mi(x, y) == pytest.approx(K.knn_mi(4 * x + 3, 4 * y - 1), abs=1e-9)
    assert K.knn_mi(x[:6], y[:6]) is None
    assert K.digamma_int(np.array([1, 2, 3])) == pytest.approx([-0.5772156649, 0.4227843351, 0.9227843351])


def test_neighbour_searches_agree():
    rng = np.random.default_rng(3)
    x, y = rng.random(150), rng.random(150)
    want = K.knn_mi(x, y)
    assert all(K.knn_mi(x, y, search=s) == pytest.approx(want, abs=1e-12) for s in ("box", "kdtree", "projection"))


def test_box_example():
    """Two neighbours of a point lie within the counts of both axes; arrivals hit one case each."""
    x = np.array([0.0, 1.0, -1.0, 0.5, 8.0, 9.0, -9.0])
    y = np.array([0.0, 1.0, -1.0, 7.0, 0.5, 9.0, -9.0])
    d, dx, dy, _, _ = K.brute(x, y, 2)
    assert (d[0], dx[0], dy[0]) == (1, 1, 1)
    assert K.counted(np.sort(x), x[:1], dx[:1])[0] == 3 and K.counted(np.sort(y), y[:1], dy[:1])[0] == 3
    for px, py, nx, ny in ((20.0, 0.2, 3, 4), (0.2, 20.0, 4, 3), (20.0, 20.0, 3, 3)):
        k = K.IncrementalKnn(np.r_[x, px], np.r_[y, py], 2)
        k.slide(0, 7)
        k.slide(0, 8)
        assert (k.nx[0], k.ny[0], k.d[0]) == (nx, ny, 1)
    k = K.IncrementalKnn(np.r_[x, 0.1], np.r_[y, 0.1], 2)
    k.slide(0, 7)
    k.slide(0, 8)
    assert k.d[0] == 1 and k.counters["researched"] > 0


@pytest.mark.parametrize("step", [5, 20])
def test_incremental_equals_scratch(step):
    x, y = gauss(0.45, 260, step)
    k = K.IncrementalKnn(x, y, 6)
    for s in range(0, 161, step):
        assert k.slide(s, s + 100) == pytest.approx(K.knn_mi(x[s : s + 100], y[s : s + 100]), abs=1e-12)
    c = k.counters
    assert c["untouched"] + c["researched"] + c["recounted"] > 0 and k.state_bytes() == 260 * 8 * (2 * 16 + 6)


@pytest.mark.parametrize("n,step,ties", [(1500, 60, False), (1500, 700, False), (300, 7, True), (1300, 40, True), (40, 3, True)])
def test_incremental_equals_scratch_in_boxes_and_with_ties(n, step, ties):
    x, y = gauss(0.6, 2 * n, step)
    if ties:
        x, y = np.round(x * 2), np.round(y * 2)
    k = K.IncrementalKnn(x, y, 6)
    for s in range(0, n, step):
        assert k.slide(s, s + n) == pytest.approx(K.knn_mi(x[s : s + n], y[s : s + n]), abs=1e-12)
    for s in range(n, 0, -3 * step):
        assert k.slide(s, s + n) == pytest.approx(K.knn_mi(x[s : s + n], y[s : s + n]), abs=1e-12)


def test_boxes_find_the_nearest():
    rng = np.random.default_rng(3)
    for x, y in ((rng.random(1200), rng.random(1200)), (np.zeros(50), np.zeros(50)), (np.arange(300.0), np.zeros(300)), (rng.exponential(size=900) ** 6, rng.random(900)), (np.round(rng.random(700) * 5), np.round(rng.random(700) * 5))):
        rows = np.arange(0, len(x), 3)
        for size in (1, 6, 16, 60):
            for got, want in zip(K.Boxes(x, y).nearest(rows, size), K.matrix_nearest(x, y, rows, size), strict=True):
                assert (got == want).all()


def test_rectangle_misses_neighbours():
    wrong = 0
    for seed in range(5):
        x, y = gauss(0.45, 260, seed)
        k = K.IncrementalKnn(x, y, 6, "rect")
        wrong += sum(abs(k.slide(s, s + 100) - K.knn_mi(x[s : s + 100], y[s : s + 100])) > 1e-12 for s in range(0, 161, 20))
    assert wrong > 0


def test_scan_semantics():
    passes = {20}
    rows = lambda a, b: {"mi": float(a in passes)}
    chosen, left, _ = K.scan(np.zeros(50), np.zeros(50), 0, 50, 10, 10, lambda r: r["mi"] > 0, scores=rows)
    assert [(r["s"], r["e"]) for r in chosen] == [(20, 30)] and left == [(0, 20), (30, 50)]
    chosen, left, _ = K.scan(np.zeros(7), np.zeros(7), 0, 7, 10, 1, lambda r: True, scores=rows)
    assert chosen == [] and left == [(0, 7)]


def test_grid_greedy_is_the_scan(spark):
    rng = np.random.default_rng(1)
    pairs, want = [], set()
    for t in range(40):
        ok = {s for s in range(0, 120, 5) if rng.random() < 0.4}
        pairs += [(str(t), s, s + 20) for s in ok if s + 20 <= 120]
        chosen, _, _ = K.scan(np.zeros(120), np.zeros(120), 0, 120, 20, 5, lambda r: r["mi"] > 0, scores=lambda a, b, ok=ok: {"mi": float(a in ok)})
        want |= {(str(t), r["s"], r["e"]) for r in chosen}
    df = spark.createDataFrame(pairs, "pair_id string, s long, e long")
    assert {tuple(r) for r in W.greedy(df, ["pair_id"]).collect()} == want


@pytest.fixture(scope="module")
def pair(spark):
    n = 240
    base = synth.relation(spark, "independent", n).withColumn("y", F.when((F.col("idx") >= 60) & (F.col("idx") < 120), F.col("x") + 0.02 * F.col("y")).otherwise(F.col("y")))
    return base.withColumn("pair_id", F.lit("p")).cache()


def test_executors(spark, pair):
    ladder, rule = W.Ladder.of((48, 12), (24, 6)), W.Absolute(0.7)
    a, left, counts = search.layered_search(pair, ladder, rule, "sequential", tie=None)
    b, left_b, _ = search.layered_search(pair, ladder, rule, "grid", tie=None)
    brute, _, work = search.layered_search(pair, ladder, rule, "sequential", incremental=False, tie=None)
    assert a.count() and W.same(a, b) and W.same(a, brute) and W.same(left, left_b)
    total = a.agg(F.sum(F.col("e") - F.col("s"))).first()[0] + left.agg(F.sum(F.col("e") - F.col("s"))).first()[0]
    assert total == 240
    assert counts.agg(F.sum("added")).first()[0] < work.agg(F.sum("added")).first()[0]
    c, _, _ = search.layered_search(pair, ladder, rule, "chunked", windows_per_chunk=2, tie=None)
    assert c.where(F.col("mi") < 0.7).isEmpty() and not c.isEmpty()
    found = evaluate.recovery(a, synth.truth(spark, [(60, 120, "linear")], "p")).first()
    assert found["iou"] > 0.3


def test_chunked_searches_are_disjoint_and_miss_nothing(spark):
    """Dependence across chunk borders: no two windows overlap, all pass, and what is left has no passing grid window."""
    n = 288
    base = synth.relation(spark, "linear", n).withColumn("pair_id", F.lit("a"))
    mixed = synth.relation(spark, "independent", n, salt="q").withColumn("y", F.when(F.col("idx").between(70, 130), F.col("x")).otherwise(F.col("y"))).withColumn("pair_id", F.lit("b"))
    paired, ladder = base.unionByName(mixed).cache(), W.Ladder.of((48, 12), (24, 6))
    grid = {g: {(r["pair_id"], r["s"]) for r in search.score_windows(search.untied(paired), W.grid(W.whole(paired), g, step), g, {"tie": None}).where("mi >= 0.6").collect()} for g, step in ((48, 12), (24, 6))}
    for executor in ("chunked", "recursive"):
        found, left, counts = search.layered_search(paired, ladder, W.Absolute(0.6), executor, windows_per_chunk=2)
        rows, spans = found.collect(), [tuple(r) for r in left.select("pair_id", "s", "e").collect()]
        assert all(r["mi"] >= 0.6 for r in rows) and counts.count() >= 3
        for p in "ab":
            own = sorted([(r["s"], r["e"]) for r in rows if r["pair_id"] == p] + [(s, e) for q, s, e in spans if q == p])
            assert own[0][0] == 0 and own[-1][1] == n and all(a[1] == b[0] for a, b in zip(own, own[1:]))
        assert [r["s"] for r in sorted(rows, key=lambda r: r["s"]) if r["pair_id"] == "a"] == list(range(0, n, 48))
        inside = [(p, s, g) for g, starts in grid.items() for p, s in starts if any(p == q and a <= s and s + g <= b for q, a, b in spans)]
        assert not inside


def test_grid_equals_scan_with_ties(spark):
    paired = synth.relation(spark, "linear", 240).withColumn("x", F.floor(F.col("x") * 4)).withColumn("y", F.floor(F.col("y") * 4)).withColumn("pair_id", F.lit("t"))
    a, b = (search.layered_search(paired, W.Ladder.of((48, 12), (24, 6)), W.Absolute(0.35), e)[0] for e in ("sequential", "grid"))
    assert a.count() and sorted((r["s"], r["e"], round(r["mi"], 9)) for r in a.collect()) == sorted((r["s"], r["e"], round(r["mi"], 9)) for r in b.collect())


def test_islands_over_stretches(spark, monkeypatch):
    monkeypatch.setattr(W, "STRETCH", 16)
    rng = np.random.default_rng(5)
    rows = [(p, int(s), int(s + n)) for p in "pq" for s, n in zip(rng.integers(0, 400, 60), rng.integers(1, 30, 60))]
    df = spark.createDataFrame(rows, "pair_id string, s long, e long")
    kept = [tuple(r) for r in W.disjoint(df).collect()]
    want = []
    for p, s, e in sorted(set(rows), key=lambda r: (r[0], r[1] - r[2], r[1])):
        if not any(p == q and s < b and a < e for q, a, b in want):
            want.append((p, s, e))
    assert sorted(kept) == sorted(want)
    left = W.leftouts(spark.createDataFrame([("p", 0, 450), ("q", 0, 200), ("q", 200, 450)], "pair_id string, s long, e long"), W.disjoint(df).where("s >= 200 or e <= 200"))
    points = {(p, i) for p, s, e in want if s >= 200 or e <= 200 for i in range(s, e)}
    assert {(r["pair_id"], i) for r in left.collect() for i in range(r["s"], r["e"])} == {(p, i) for p in "pq" for i in range(450)} - points
    union = {(r["pair_id"], r["s"], r["e"]) for r in W.merge(df, "union").collect()}
    covered = {(p, i) for p, s, e in rows for i in range(s, e)}
    assert {(p, i) for p, s, e in union for i in range(s, e)} == covered


def test_distributed_estimator_of_flat_series(spark):
    for x, y in ((F.lit(1.0), F.lit(2.0)), (F.lit(1.0), F.col("id") * 1.0)):
        p = spark.range(40).select(F.lit("p").alias("pair_id"), F.col("id").alias("idx"), x.alias("x"), y.alias("y"))
        rows = p.orderBy("idx").toPandas()
        assert search.knn_mi_distributed(p).first()["mi"] == pytest.approx(K.knn_mi(rows["x"], rows["y"]), abs=1e-9)


def test_distributed_estimator(spark, pair):
    rows = pair.orderBy("idx").toPandas()
    got = search.knn_mi_distributed(pair).first()["mi"]
    assert got == pytest.approx(K.knn_mi(rows["x"], rows["y"]), abs=1e-9)


def test_panes_equal_windows(pair):
    got = {r["s"]: r["mi"] for r in panes.scores(pair, 48, 12, 6).collect()}
    rows = pair.orderBy("idx").toPandas()
    bx, by = (K.equal_width(rows[c], 6) for c in "xy")
    assert len(got) == 17
    for s, mi in got.items():
        assert mi == pytest.approx(K.plugin(bx[s : s + 48], by[s : s + 48])["mi"], abs=1e-9)


def test_information_bounds(pair):
    out = M.normalised(M.information(M.by_width(pair, ["x", "y"], 6, ["pair_id"]), "b_x", "b_y", ["pair_id"]))
    r = out.select("*", M.bounds_ok().alias("ok")).first()
    assert r["ok"] and 0 <= r["mi_norm2"] <= 1 and 0 <= r["h_norm"] <= 1


def test_directions(spark):
    rows = [("up", i, float(i), float(i)) for i in range(5)] + [("down", i, float(i), float(-i)) for i in range(5)] + [("tie", i, 1.0, float(i)) for i in range(5)] + [("one", 0, 1.0, 1.0)]
    got = {r["pair_id"]: r for r in M.directions(spark.createDataFrame(rows, "pair_id string, idx long, x double, y double"), ["pair_id"]).collect()}
    assert (got["up"]["mu"], got["up"]["sign"], got["up"]["conf"]) == (1, "positive", 1)
    assert (got["down"]["mu"], got["down"]["sign"], got["down"]["conf"]) == (-1, "negative", 1)
    assert got["tie"]["mu"] == 0 and got["tie"]["sign"] == "neither" and got["one"]["mu"] is None


def test_coverage_and_merging(spark):
    sel = spark.createDataFrame([("p", 0, 50), ("p", 50, 100), ("p", 20, 40)], "pair_id string, s long, e long")
    assert W.coverage(sel, spark.createDataFrame([("p", 500)], "pair_id string, n long")).first()["coverage"] == 0.2
    assert {(r["s"], r["e"]) for r in W.merge(sel).collect()} == {(0, 50), (50, 100)}
    left = W.leftouts(spark.createDataFrame([("p", 0, 120), ("q", 5, 9)], "pair_id string, s long, e long"), sel)
    assert {(r["pair_id"], r["s"], r["e"]) for r in left.collect()} == {("p", 100, 120), ("q", 5, 9)}


def test_thresholds(pair):
    scores = search.score_windows(pair, W.grid(W.whole(pair), 48, 12), 48, {"tie": None}).cache()
    sizes = pair.groupBy("pair_id").agg(F.count("*").alias("n"))
    r = search.tune_sigma(scores, sizes, 0.2, [0.1, 0.5, 0.9, 1.3]).first()
    assert abs(r["coverage"] - 0.2) <= 0.2
    assert W.TwoStep(0.2, 0.2)({"h_norm": 0.1, "mi_norm1": 1, "mi_norm2": 1}) is False
    k = search.tune_k(pair.where("idx < 100"), range(1, 8)).toPandas()
    assert len(k) == 7 and k["spread"].notna().all()


def test_relations(spark):
    got = {k: K.knn_mi(*synth.relation(spark, k, 600).orderBy("idx").toPandas()[["x", "y"]].to_numpy().T) for k in synth.KINDS}
    assert abs(got["independent"]) < 0.12 and all(got[k] > 0.15 for k in synth.KINDS if k not in ("independent", "independent_outliers"))
    assert got["linear"] > got["linear_outliers"]
    x, y = synth.relation(spark, "circle", 300).toPandas()[["x", "y"]].to_numpy().T
    assert abs(np.corrcoef(x, y)[0, 1]) < 0.2 and K.kde_mi(x, y) > 0.1 and K.dcor(x, y) < 0.5
    assert K.total_correlation([x, y, x]) > K.total_correlation([x, y])


def test_prep(spark):
    s = spark.createDataFrame([("v", 2, 2.0), ("v", 6, 6.0), ("w", 0, 1.0)], "var string, idx long, v double")
    full = prep.interpolate(prep.spine(s, 0, 8), chunk=3)
    assert [r["v"] for r in full.where("var = 'v'").orderBy("idx").collect()] == [2, 2, 2, 3, 4, 5, 6, 6]
    assert prep.interpolate(prep.spine(s, 0, 8), hold=False).where("var = 'v'").count() == 5
    again = prep.unpack(prep.pack(full, 3))
    assert again.exceptAll(full.select("var", "idx", "v")).isEmpty()
    assert [r["y"] for r in prep.asof(spark.createDataFrame([("v", i, 0.0) for i in (1, 3, 9)], "var string, idx long, v double"), s, 2).orderBy("idx").collect()] == [None, 2.0, None]
    assert prep.all_pairs(full, 4, tiles=3).count() == 8
    assert prep.coarser(full, 4).count() == 4 and prep.finer(s, 2).count() == 6
    assert prep.enumerate_pairs(s.select("var").distinct()).count() == 1


def test_sources(spark, tmp_path):
    (tmp_path / "a.csv").write_text("idx,v\n1,2.5\nx,y\n")
    got = tables.load_text(spark, str(tmp_path / "a.csv"), "csv", "idx long, v double").collect()
    assert got[0]["v"] == 2.5 and got[1]["_bad"] is not None
    w = spark.createDataFrame([("p", 0, 1.0), ("p", 1, 2.0)], "pair_id string, layer int, mi double")
    tables.save_windows(w, str(tmp_path / "w"))
    tables.save_windows(w.where("layer = 1").withColumn("mi", F.lit(3.0)), str(tmp_path / "w"))
    assert spark.read.parquet(str(tmp_path / "w")).agg(F.sum("mi")).first()[0] == 4.0


def test_reports(spark):
    w = spark.createDataFrame([("p", 0, 0, 5, 1.0, "positive"), ("p", 1, 5, 9, 1.0, "negative"), ("q", 0, 0, 5, 2.0, "positive")], "pair_id string, layer int, s long, e long, mi double, sign string")
    assert [r["pair_id"] for r in W.rank(w, k=2).collect()] == ["q", "p"]
    assert W.rank(w, k=1, per_pair=True).count() == 2 and W.rollup(w).count() == 6 and W.cube(w).count() > 6 and W.summary(w).count() == 2


def test_sql_surface(spark, pair):
    sql.register(spark)
    pair.createOrReplaceTempView("paired")
    r = spark.sql("select pair_id, knn_mi_agg(x, y, 6) m, dcor_agg(x, y) d from paired group by pair_id").first()
    assert r["m"] > -0.2 and 0 <= r["d"] <= 1
    found = spark.sql("select * from correlation_windows(table(paired) partition by pair_id order by (idx), 48, 12, 0.7D)").collect()
    assert found and all(x["mi"] >= 0.7 for x in found)


def streamed(spark, tmp_path, parts, **options):
    """What a search over a stream gives whose batches are the given rows (idx, x, y)."""
    schema = "pair_id string, idx long, x double, y double"
    for part in parts:
        spark.createDataFrame([("p", *r) for r in part], schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        import time

        time.sleep(0.05)  # files are taken by their time
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    name = "found" + tmp_path.name.replace("-", "_")
    q = live.stream_search(stream, W.Ladder.of((48, 12), (24, 6)), W.Absolute(0.7), **options).writeStream.format("memory").queryName(name).outputMode("append").start()
    q.processAllAvailable()
    q.stop()
    return [tuple(r) for r in spark.table(name).collect()]


def test_stream_search_of_all_layers_equals_batch(spark, pair, tmp_path):
    rows = [tuple(r) for r in pair.orderBy("idx").select("idx", "x", "y").collect()]
    parts = [rows[i::3] for i in range(3)] + [[(240, None, None)]]
    got = {(r[1], r[2], r[3]) for r in streamed(spark, tmp_path, parts)}
    found = search.layered_search(pair, W.Ladder.of((48, 12), (24, 6)), W.Absolute(0.7), tie=None)[0]
    want = {(r["layer"], r["s"], r["e"]) for r in found.collect()}
    assert got == want and len({w[0] for w in want}) == 2


def test_stream_search_with_gaps_and_revisions(spark, pair, tmp_path):
    rows = [tuple(r) for r in pair.orderBy("idx").select("idx", "x", "y").collect()]
    holes = [r for r in rows if r[0] != 30]
    again = [(r[0], r[1], -r[2]) for r in rows if 80 <= r[0] < 84]
    got = streamed(spark, tmp_path, [holes[:150], [(30, 0.5, 0.5)], again, holes[150:], [(240, None, None)]], lateness=50, remember=150)
    x, y = ([r[i] for r in rows] for i in (1, 2))
    want = set()
    for s, e in ((0, 30), (31, 240)):
        want |= {(i, r["s"], r["e"]) for i, r in K.top_down(np.array(x), np.array(y), s, e, [(48, 12), (24, 6)], lambda i: W.Absolute(0.7), tie=None)[0]}
    assert {r[1:4] for r in got if r[5] == 0} == want
    changed = [r for r in got if r[5] == 1]
    assert changed and all(r[2] < 84 and r[3] > 80 for r in changed) and all(r[6] == (r[4] >= 0.7) for r in changed)


def test_plans(spark, small):
    df = prep.extract(tables.load(spark, small, "events"), prep.VariableSpec("v", "ts", F.sum("value"), where=F.col("event_type") == "click"))
    plan = df._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(event_type), EqualTo(event_type,click)]" in plan and "props" not in plan.split("ReadSchema")[1]


def test_planner():
    assert search.choose_executor(100, 0.1, True, 8) == "sequential" and search.choose_executor(2, 0.9, True, 8) == "grid" and search.choose_executor(2, 0.9, False, 8) == "chunked"
    assert search.chunk_bounds(720, 168, 2) == [(0, 336), (168, 672), (504, 720)]
    assert "layer 1" in search.explain_search(1000, W.Ladder.of((100, 10), (50, 5)), "grid")
    assert [x.size for x in W.Ladder.calendar("1H").layers] == [8760, 720, 168, 24] and [x.size for x in W.Ladder.arithmetic(30, 10, 10, 2).layers] == [30, 20, 10]


def test_oracles(spark, small):
    """Every query with SQL gives the same as DuckDB on the smallest tables."""
    import duckdb

    from tempcorr.workloads import oracle_sql, queries

    c = duckdb.connect()
    for t in "orders lineitem events documents labels conversations".split():
        c.sql(f"create view {t} as select * from '{small}/{t}.parquet'")
    known = oracle_sql()
    for name in ("overall_plugin_mi", "direction", "interpolate", "all_pairs_rank", "categorical_mi", "pearson_pairs", "knn_mi_windows"):
        df = queries()[name](spark, small)
        r = c.sql(known[name])
        assert sorted(map(str, (tuple(x[k] for k in r.columns) for x in df.collect()))) == sorted(map(str, r.fetchall())), name


def test_pandas_is_there():
    assert pd.__version__
