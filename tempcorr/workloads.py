"""The engine's methods on the given tables, by name, and SQL for what SQL can express."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tempcorr import evaluate
from tempcorr import search_forms as S
from tempcorr.functions import kernel
from tempcorr.functions import measures as M
from tempcorr.operators import panes, prep
from tempcorr.operators import windows as W
from tempcorr.plans import search
from tempcorr.sources import synth
from tempcorr.sources.tables import load
from tempcorr.streaming import live

SIGMA = 0.45
SPANS = [(168, 336, "linear"), (500, 548, "linear")]
FOUR = [(240, 360, "cross"), (600, 720, "diamond"), (960, 1080, "sine"), (1320, 1440, "quadratic")]
WHOLE = [(-(1 << 40), 1 << 40, "linear")]
LADDER = W.Ladder.of((168, 24), (48, 12), (24, 6))


def r6(c: str):
    return (F.round(c, 6) + F.lit(0.0)).alias(c)


def hourly(spark, d, name, value, where=None) -> DataFrame:
    return prep.extract(load(spark, d, "events"), prep.VariableSpec(name, "ts", value, where=where))


def daily(spark, d, table, ts, name, value) -> DataFrame:
    return prep.extract(load(spark, d, table), prep.VariableSpec(name, ts, value, "1D", "1995-01-01"))


def money(c: str):
    return F.round(F.sum(c), 2)


def pair(spark, d, name) -> DataFrame:
    """The natural pairs, on the steps that both series have."""
    n = F.count("*")
    v = {
        "EV_SUM": lambda: (hourly(spark, d, "n", n), hourly(spark, d, "v", money("value"))),
        "EV_USERS": lambda: (hourly(spark, d, "n", n), hourly(spark, d, "u", F.count_distinct("user_id"))),
        "EV_AVG": lambda: (hourly(spark, d, "n", n), hourly(spark, d, "a", F.round(F.round(F.sum("value"), 2) / n, 6))),
        "EV_CLICK_BUY": lambda: (hourly(spark, d, "c", n, F.col("event_type") == "click"), hourly(spark, d, "b", n, F.col("event_type") == "purchase")),
        "ORD_REV": lambda: (daily(spark, d, "orders", "o_orderdate", "n", n), daily(spark, d, "orders", "o_orderdate", "v", money("o_totalprice"))),
        "SHIP_QTY": lambda: (daily(spark, d, "lineitem", "l_shipdate", "n", n), daily(spark, d, "lineitem", "l_shipdate", "q", money("l_quantity"))),
        "QTY_PRICE": lambda: (daily(spark, d, "lineitem", "l_shipdate", "q", money("l_quantity")), daily(spark, d, "lineitem", "l_shipdate", "p", money("l_extendedprice"))),
    }[name]()
    return prep.align(*v, name)


def pairs(spark, d, names=("EV_SUM", "EV_USERS", "ORD_REV", "SHIP_QTY")) -> DataFrame:
    out = pair(spark, d, names[0])
    for n in names[1:]:
        out = out.unionByName(pair(spark, d, n))
    return out


def planted(spark, d, spans=None, name="PL") -> DataFrame:
    base = hourly(spark, d, name, F.round(F.round(F.sum("value"), 2) / F.count("*"), 6))
    return synth.plant(prep.even(base), spans or SPANS)


def four(spark, d) -> DataFrame:
    base = prep.extract(load(spark, d, "events"), prep.VariableSpec("PL_FOUR", "ts", F.round(F.round(F.sum("value"), 2) / F.count("*"), 6), "15M"))
    return synth.plant(prep.even(base), FOUR)


def plugin_scores(spark, d) -> DataFrame:
    out = M.normalised(M.information(M.by_width(pairs(spark, d), ["x", "y"], 6, ["pair_id"]), "b_x", "b_y", ["pair_id"]))
    return out.select("pair_id", "n", *[r6(c) for c in ("hx", "hy", "hxy", "mi", "h_norm", "mi_norm1", "mi_norm2")])


def categorical(spark, d) -> DataFrame:
    out = None
    for name, table, x, y in (("flag_status", "lineitem", "l_returnflag", "l_linestatus"), ("lang_source", "documents", "lang", "source"), ("quality_toxic", "labels", "quality", "toxic"), ("role_turn", "conversations", "role", "turn")):
        got = M.information(load(spark, d, table).select(F.lit(name).alias("pair_id"), F.col(x).cast("string").alias("x"), F.col(y).cast("string").alias("y")), "x", "y", ["pair_id"])
        out = got if out is None else out.unionByName(got)
    return out.select("pair_id", "n", *[r6(c) for c in ("hx", "hy", "hxy", "mi")])


def per_pair(paired: DataFrame, schema: str, f) -> DataFrame:
    return paired.groupBy("pair_id").applyInPandas(lambda df: f(df["pair_id"].iloc[0], df.sort_values("idx")), schema)


def knn_overall(spark, d) -> DataFrame:
    f = lambda p, df: pd.DataFrame([(p, len(df), kernel.knn_mi(df["x"], df["y"], 6))], columns=["pair_id", "n", "mi"])
    return per_pair(pairs(spark, d, ("EV_SUM", "EV_USERS")), "pair_id string, n long, mi double", f).select("pair_id", "n", r6("mi"))


def knn_windows(spark, d) -> DataFrame:
    p = prep.align(prep.even(hourly(spark, d, "n", F.count("*"))), prep.even(hourly(spark, d, "v", money("value"))), "EV_SUM")
    return search.score_windows(p, W.grid(W.whole(p), 48, 24), 48, {"k": 6, "tie": None}).select("s", "e", "n", r6("mi"))


def k_sweep(spark, d) -> DataFrame:
    def f(p, df):
        mi = [kernel.knn_mi(df["x"], df["y"], k) for k in range(1, 21)]
        return pd.DataFrame({"pair_id": p, "k": range(1, 21), "mi": mi})

    return per_pair(pair(spark, d, "EV_SUM"), "pair_id string, k long, mi double", f).select("k", r6("mi"))


def direction(spark, d) -> DataFrame:
    return M.directions(pairs(spark, d), ["pair_id"]).select("pair_id", "n", "pp", "np", r6("mu"), "sign", r6("conf"))


def pearson(spark, d) -> DataFrame:
    return M.linear(pairs(spark, d), ["pair_id"]).select("pair_id", "n", r6("pearson"))


def dcor(spark, d) -> DataFrame:
    f = lambda p, df: pd.DataFrame([(p, len(df), kernel.dcor(df["x"], df["y"]))], columns=["pair_id", "n", "dcor"])
    return per_pair(pairs(spark, d, ("EV_SUM", "EV_USERS")), "pair_id string, n long, dcor double", f).select("pair_id", "n", r6("dcor"))


def resample_hour(spark, d) -> DataFrame:
    return prep.align(hourly(spark, d, "n", F.count("*")), hourly(spark, d, "v", money("value")), "h").select("idx", F.col("x").cast("long").alias("n"), F.col("y").alias("v"))


def interpolated(spark, d) -> DataFrame:
    s = prep.extract(load(spark, d, "events"), prep.VariableSpec("q", "ts", money("value"), "15M"))
    return prep.interpolate(prep.spine(s, *prep.horizon(s)), chunk=256).select("idx", r6("v"), "imputed")


def grid(spark, d) -> DataFrame:
    return panes.scores(pair(spark, d, "EV_SUM"), 48, 12, 6)


def grid_scores(spark, d) -> DataFrame:
    return grid(spark, d).select("s", "e", "n", *[r6(c) for c in ("hx", "hy", "hxy", "mi", "h_norm", "mi_norm1", "mi_norm2")])


def chosen(spark, d) -> DataFrame:
    return W.greedy(grid(spark, d).where(F.round("mi", 6) >= SIGMA).select("pair_id", "s", "e"), ["pair_id"])


def segments(spark, d) -> DataFrame:
    return W.whole(pair(spark, d, "EV_SUM"))


def sizes(spark, d) -> DataFrame:
    return segments(spark, d).select("pair_id", (F.col("e") - F.col("s")).alias("n"))


def sigma_sweep(spark, d) -> DataFrame:
    sigmas = spark.createDataFrame([(i / 20,) for i in range(4, 15)], "sigma double")
    passing = grid(spark, d).crossJoin(F.broadcast(sigmas)).where(F.round("mi", 6) >= F.col("sigma"))
    covered = W.greedy(passing.select("sigma", "s", "e"), ["sigma"]).groupBy("sigma").agg(F.sum(F.col("e") - F.col("s")).alias("c"))
    return covered.crossJoin(F.broadcast(sizes(spark, d))).select("sigma", F.round(F.col("c") / F.col("n"), 6).alias("coverage"))


def topk(spark, d) -> DataFrame:
    return W.rank(grid(spark, d).withColumn("mi", F.round("mi", 6)), "mi", 11).select("s", "e", "n", "mi", r6("mi_norm2"))


def layered(executor, **more):
    def run(spark, d):
        return search.layered_search(planted(spark, d), LADDER, W.Absolute(0.6), executor, **more)[0].select("pair_id", "layer", "s", "e", r6("mi"), r6("mi_norm2"), "sign")

    return run


def counters(spark, d) -> DataFrame:
    """Work of a scan that keeps its state, and of one that starts anew in each window."""
    out = None
    for name, incremental in (("incremental", True), ("brute", False)):
        got = search.layered_search(planted(spark, d), LADDER, W.Absolute(0.6), "sequential", incremental=incremental)[2].withColumn("method", F.lit(name))
        out = got if out is None else out.unionByName(got)
    return out.groupBy("method").agg(*[F.sum(c).alias(c) for c in search.COUNTERS])


def recovery(spark, d) -> DataFrame:
    found = search.layered_search(planted(spark, d), LADDER, W.Absolute(0.6), "grid")[0]
    return evaluate.recovery(found, synth.truth(spark, SPANS, "PL")).select("s", "e", r6("iou"), "start_error", "end_error")


def thresholds(spark, d) -> DataFrame:
    """Windows chosen at each threshold, by either normalisation, and how many of them are meaningful."""
    p, out = search.cut(four(spark, d)), None
    scores = search.cut(search.score_windows(p, W.grid(W.whole(p), 120, 12), 120, {"k": 6, "tie": None}))
    for by in ("mi_norm1", "mi_norm2"):
        got = evaluate.threshold_effects(scores, synth.truth(spark, FOUR, "PL_FOUR"), [i / 20 for i in range(1, 20)], by).select(F.lit(by).alias("norm"), "sigma", "total", "meaningful")
        out = got if out is None else out.unionByName(got)
    return out


def relations(spark, d) -> DataFrame:
    """A pair for each relation over the whole of one table series."""
    base, out = search.cut(prep.even(hourly(spark, d, "all", F.round(F.round(F.sum("value"), 2) / F.count("*"), 6)))), None
    for kind in synth.KINDS:
        got = synth.plant(base.withColumn("var", F.lit(kind)), [(-(1 << 40), 1 << 40, kind)])
        out = got if out is None else out.unionByName(got)
    return out


def metric_table(spark, d) -> DataFrame:
    return evaluate.identify_table(relations(spark, d), 0.02, 49)


def relation_scores(spark, d) -> DataFrame:
    """Every relation by nearest neighbours, its normalised form, Pearson's coefficient, covariance and distance correlation."""
    p = search.cut(relations(spark, d))
    return search.overall(p, k=6, tie=None).select("pair_id", "n", r6("mi"), r6("mi_norm2"), r6("dcor")).join(M.linear(p, ["pair_id"]).select("pair_id", r6("pearson"), r6("covariance")), "pair_id")


def four_windows(spark, d) -> DataFrame:
    """The four relations of one series by windows: which span a window meets most."""
    found = search.layered_search(four(spark, d), W.Ladder.of((120, 12), (60, 12)), W.Absolute(0.6))[0]
    truth = synth.truth(spark, FOUR, "PL_FOUR").select("relation", F.col("s").alias("ts"), F.col("e").alias("te"))
    common = F.least("e", "te") - F.greatest("s", "ts")
    near = found.join(F.broadcast(truth), common > 0, "left").groupBy("pair_id", "layer", "s", "e", "mi").agg(F.max_by("relation", common).alias("relation"))
    return near.select("layer", "s", "e", r6("mi"), "relation")


def exhaustive(spark, d) -> DataFrame:
    return search.exhaustive(planted(spark, d), 24, 48, 12, k=6, tie=None).select("s", "e", r6("mi"), r6("mi_norm1"))


def by_frequency(spark, d) -> DataFrame:
    p = pairs(spark, d)
    for c in "xy":
        p = M.by_frequency(p, c, 6, ["pair_id"], ["idx"])
    return M.information(p, "b_x", "b_y", ["pair_id"]).select("pair_id", "n", r6("mi"), r6("hxy"))


def by_change(spark, d) -> DataFrame:
    p = pairs(spark, d)
    for c in "xy":
        p = M.by_change(p, c, ["pair_id"], "idx")
    return M.information(p, "b_x", "b_y", ["pair_id"]).select("pair_id", "n", r6("mi"), r6("hxy"))


def props(spark, d) -> DataFrame:
    """Two properties of one row: a value from JSON against a column."""
    e = load(spark, d, "events")
    p = e.select(F.lit("k_value").alias("pair_id"), prep.props_value(e, "k").alias("x"), F.col("value").alias("y")).where("x is not null")
    return M.information(M.by_width(p, ["x", "y"], 6, ["pair_id"]), "b_x", "b_y", ["pair_id"]).select("pair_id", "n", r6("mi"), r6("hxy"))


def components_pair(spark, d) -> DataFrame:
    """Two components of the vectors."""
    v = load(spark, d, "embeddings")
    p = prep.align(prep.embedding_component(v, 0), prep.embedding_component(v, 1), "e0_e1")
    return M.information(M.by_width(p, ["x", "y"], 6, ["pair_id"]), "b_x", "b_y", ["pair_id"]).select("pair_id", "n", r6("mi"), r6("hxy"))


def profiles(spark, d) -> DataFrame:
    s = hourly(spark, d, "n", F.count("*")).unionByName(hourly(spark, d, "v", money("value"))).unionByName(daily(spark, d, "orders", "o_orderdate", "t", money("o_totalprice")))
    return prep.profile(s).select("var", "n", "missing", "values", r6("low"), r6("high"), r6("mean"))


def outside(spark, d) -> DataFrame:
    """Points that no chosen window holds, and the others."""
    p, w = pair(spark, d, "EV_SUM"), search.cut(chosen(spark, d))
    return prep.inside(p, w, 64).withColumn("held", F.lit(True)).unionByName(prep.inside(p, w, 64, False).withColumn("held", F.lit(False))).select("idx", "held")


def streamed(spark, stream: DataFrame, mode: str = "complete") -> DataFrame:
    """What a stream gives until its source is read."""
    out = f"{search.shared_folder(spark).rstrip('/')}/tempcorr-stream-{uuid.uuid4().hex}"
    how = "overwrite" if mode == "complete" else "append"
    q = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{out}-state").foreachBatch(lambda b, i: b.write.mode(how).parquet(out)).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def event_stream(spark, d) -> DataFrame:
    return spark.readStream.schema(load(spark, d, "events").schema).option("pathGlobFilter", "events.parquet").parquet(d)


def stream_sliding(spark, d) -> DataFrame:
    s = event_stream(spark, d).select("ts", F.col("value").alias("x"), F.col("user_id").cast("double").alias("y"))
    bins = live.sliding(s, "ts", "24 hours", "12 hours", "1 hour")
    return streamed(spark, bins.select(F.timestamp_diff("HOUR", F.lit("2024-01-01").cast("timestamp"), F.col("window.start")).alias("s"), "n", F.col("pearson"))).select("s", "n", r6("pearson"))


def stream_sessions(spark, d) -> DataFrame:
    bins = live.sessions(event_stream(spark, d), "ts", "10 minutes", "1 hour", "event_type")
    return streamed(spark, bins.select("event_type", F.unix_timestamp("session_window.start").alias("since"), "n"))


def stream_search(spark, d) -> DataFrame:
    """The layered search of the planted pair, whose points come as a stream and out of order."""
    points = search.untied(planted(spark, d))
    ends = points.groupBy("pair_id").agg((F.max("idx") + 1).alias("idx")).select("pair_id", "idx", F.lit(None).cast("double").alias("x"), F.lit(None).cast("double").alias("y"))
    path = f"{search.shared_folder(spark).rstrip('/')}/tempcorr-points-{uuid.uuid4().hex}"
    points.unionByName(ends).repartition(4, F.pmod("idx", F.lit(4))).write.parquet(path)
    stream = spark.readStream.schema(points.schema).option("maxFilesPerTrigger", 1).parquet(path)
    found = live.stream_search(stream, LADDER, W.Absolute(0.6))
    return streamed(spark, found, "append").select("pair_id", "layer", "s", "e", r6("mi"))


def all_pairs(spark, d) -> DataFrame:
    """Every pair of hourly counts by type, and their sum of values, by plug-in information."""
    events = load(spark, d, "events")
    s = events.groupBy("event_type", prep.index_of(F.col("ts"), "1H", "2024-01-01").alias("idx")).agg(F.count("*").cast("double").alias("v")).select(F.col("event_type").alias("var"), "idx", "v")
    s = prep.even(s, 0.0).select("var", "idx", "v")
    got = M.information(M.by_width(prep.all_pairs(s, 240), ["x", "y"], 6, ["pair_id"]), "b_x", "b_y", ["pair_id"])
    return got.select("pair_id", "n", r6("mi"), r6("hxy"))


def chunk_bounds(spark, d) -> DataFrame:
    parts = search._chunked(segments(spark, d), 168, 2)
    return parts.select(F.floor(F.col("e") / 336.5).alias("r"), "s", "e")


def stream_replay(spark, d) -> DataFrame:
    """Hourly counts and sums by a stream over the same file; equals the batch."""
    bins = live.resample(event_stream(spark, d), "ts", "1 hour", "1 hour", F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("v"))
    return streamed(spark, bins.select(F.timestamp_diff("HOUR", F.lit("2024-01-01").cast("timestamp"), F.col("window.start")).alias("idx"), "n", "v"))


def kde(spark, d) -> DataFrame:
    f = lambda p, df: pd.DataFrame([(p, len(df), kernel.kde_mi(df["x"], df["y"]))], columns=["pair_id", "n", "mi"])
    return per_pair(pairs(spark, d, ("EV_SUM", "EV_AVG")), "pair_id string, n long, mi double", f).select("pair_id", "n", r6("mi"))


def resolutions(spark, d) -> DataFrame:
    """One planted pair by the hour and by the day: information and sign."""
    p = planted(spark, d)
    day = p.groupBy("pair_id", F.floor(F.col("idx") / 24).alias("idx")).agg(F.avg("x").alias("x"), F.avg("y").alias("y"))
    both = p.withColumn("pair_id", F.lit("hour")).unionByName(day.withColumn("pair_id", F.lit("day")).select("pair_id", "idx", "x", "y"))
    return search.overall(search.untied(both), k=6, tie=None).select("pair_id", "n", r6("mi"), r6("mu"), "sign")


def delays(spark, d) -> DataFrame:
    """The information of a pair for each delay."""
    p, out = search.cut(planted(spark, d, WHOLE)), None
    for tau in range(-3, 4):
        got = prep.lagged(p, tau).withColumn("pair_id", F.lit(f"{tau:+d}"))
        out = got if out is None else out.unionByName(got)
    return search.overall(out, k=6, tie=None).select("pair_id", "n", r6("mi"))


def queries() -> dict:
    return {
        "overall_plugin_mi": lambda s, d: plugin_scores(s, d).select("pair_id", "n", "mi"),
        "categorical_mi": categorical,
        "entropies": lambda s, d: plugin_scores(s, d).select("pair_id", "hx", "hy", "hxy"),
        "norm_mi": lambda s, d: plugin_scores(s, d).select("pair_id", "h_norm", "mi_norm1", "mi_norm2"),
        "knn_mi_overall": knn_overall,
        "knn_mi_windows": knn_windows,
        "k_sweep": k_sweep,
        "direction": direction,
        "pearson_pairs": pearson,
        "dcor_pairs": dcor,
        "resample_hour": resample_hour,
        "interpolate": interpolated,
        "pair_align": lambda s, d: pair(s, d, "EV_USERS").select("idx", "x", "y"),
        "grid_scores": grid_scores,
        "plugin_panes": lambda s, d: grid_scores(s, d).select("s", "n", "mi"),
        "layer_select": lambda s, d: chosen(s, d).select("s", "e"),
        "leftout_segments": lambda s, d: W.leftouts(segments(s, d), chosen(s, d)).select("s", "e"),
        "merged_windows": lambda s, d: W.merge(grid(s, d).where(F.round("mi", 6) >= SIGMA).select("pair_id", "s", "e"), "union").select("s", "e"),
        "coverage": lambda s, d: W.coverage(chosen(s, d), sizes(s, d)).select("pair_id", r6("coverage")),
        "sigma_sweep": sigma_sweep,
        "two_step": lambda s, d: grid_scores(s, d).where(W.TwoStep(0.2, 0.2, "n2").column()).select("s", "e", "h_norm", "mi_norm2"),
        "topk_windows": topk,
        "all_pairs_rank": all_pairs,
        "chunk_bounds": chunk_bounds,
        "stream_replay": stream_replay,
        "layered_windows": layered("sequential"),
        "layered_grid": layered("grid"),
        "layered_chunked": layered("chunked"),
        "layered_unfiltered": layered("grid", independent_layers=True),
        "brute_vs_incremental": counters,
        "planted_recovery": recovery,
        "threshold_effects": thresholds,
        "metric_table": metric_table,
        "relation_scores": relation_scores,
        "four_windows": four_windows,
        "exhaustive_windows": exhaustive,
        "frequency_mi": by_frequency,
        "change_mi": by_change,
        "props_mi": props,
        "embedding_mi": components_pair,
        "series_profile": profiles,
        "points_outside": outside,
        "stream_sliding": stream_sliding,
        "stream_sessions": stream_sessions,
        "stream_search": stream_search,
        "layered_recursive": layered("recursive"),
        "kde_mi": kde,
        "knn_mi_distributed": lambda s, d: search.knn_mi_distributed(planted(s, d, WHOLE)).select("pair_id", r6("mi")),
        "by_resolution": resolutions,
        "delays": delays,
    }


def oracle_sql() -> dict[str, str]:
    hour = "CAST(date_diff('hour', TIMESTAMP '2024-01-01', ts) AS BIGINT)"
    day = "CAST(date_diff('day', TIMESTAMP '1995-01-01', {}) AS BIGINT)"
    six = "(round({0}, 6) + 0.0) AS {0}"
    ev = f"SELECT 'EV_SUM' AS pair_id, {hour} AS idx, CAST(count(*) AS DOUBLE) AS x, round(sum(value), 2) AS y FROM events GROUP BY ALL"
    users = f"SELECT 'EV_USERS' AS pair_id, {hour} AS idx, CAST(count(*) AS DOUBLE) AS x, CAST(count(DISTINCT user_id) AS DOUBLE) AS y FROM events GROUP BY ALL"
    orders = f"SELECT 'ORD_REV' AS pair_id, {day.format('o_orderdate')} AS idx, CAST(count(*) AS DOUBLE) AS x, round(sum(o_totalprice), 2) AS y FROM orders GROUP BY ALL"
    ship = f"SELECT 'SHIP_QTY' AS pair_id, {day.format('l_shipdate')} AS idx, CAST(count(*) AS DOUBLE) AS x, round(sum(l_quantity), 2) AS y FROM lineitem GROUP BY ALL"
    p4, p2 = f"p AS ({ev} UNION ALL {users} UNION ALL {orders} UNION ALL {ship})", f"p AS ({ev} UNION ALL {users})"

    def bins(source: str) -> str:
        one = "CASE WHEN max({0}) OVER w = min({0}) OVER w THEN 0 ELSE CAST(least(floor(({0} - min({0}) OVER w) / (max({0}) OVER w - min({0}) OVER w) * 6), 5) AS INT) END AS {1}"
        return f"SELECT *, {one.format('x', 'bx')}, {one.format('y', 'b_y')} FROM {source} WINDOW w AS (PARTITION BY pair_id)"

    def info(cells: str, by: str) -> str:
        """From rows (by, bx, by_) to n, hx, hy, hxy, mi."""
        return f"""c AS (SELECT {by}, bx, b_y, count(*) AS c FROM {cells} GROUP BY ALL),
        t AS (SELECT *, sum(c) OVER (PARTITION BY {by}, bx) AS cx, sum(c) OVER (PARTITION BY {by}, b_y) AS cy, sum(c) OVER (PARTITION BY {by}) AS n FROM c),
        i AS (SELECT {by}, CAST(n AS BIGINT) AS n, sum(-c / n * ln(cx / n)) AS hx, sum(-c / n * ln(cy / n)) AS hy, sum(-c / n * ln(c / n)) AS hxy, sum(c / n * ln(c * n / (cx * cy))) AS mi FROM t GROUP BY {by}, n),
        j AS (SELECT *, hxy / ln(n) AS h_norm, mi / ln(n) AS mi_norm1, CASE WHEN hxy > 0 THEN mi / hxy END AS mi_norm2 FROM i)"""

    cols = lambda *c: ", ".join(six.format(x) for x in c)
    plug = f"WITH {p4}, b AS (SELECT pair_id, bx, b_y FROM ({bins('p')})), {info('b', 'pair_id')}"
    cat = " UNION ALL ".join(f"SELECT '{n}' AS pair_id, CAST({x} AS VARCHAR) AS bx, CAST({y} AS VARCHAR) AS b_y FROM {t} WHERE {x} IS NOT NULL AND {y} IS NOT NULL" for n, t, x, y in (("flag_status", "lineitem", "l_returnflag", "l_linestatus"), ("lang_source", "documents", "lang", "source"), ("quality_toxic", "labels", "quality", "toxic"), ("role_turn", "conversations", "role", "turn")))
    win = f"p AS ({ev}), b AS (SELECT w.g AS s, w.g + 48 AS e, bx, b_y FROM ({bins('p')}) q JOIN (SELECT CAST(unnest(range(0, (SELECT max(idx) - 46 FROM p), 12)) AS BIGINT) AS g) w ON q.idx >= w.g AND q.idx < w.g + 48 WHERE w.g + 48 <= (SELECT max(idx) + 1 FROM p)), {info('b', 's, e')}"
    passing = f"{win}, ok AS (SELECT s, e FROM j WHERE round(mi, 6) >= {SIGMA})"
    greedy = "g AS (SELECT * FROM (SELECT s, e FROM ok ORDER BY s LIMIT 1) UNION ALL SELECT n.s, n.e FROM g, LATERAL (SELECT ok.s, ok.e FROM ok WHERE ok.s >= g.e ORDER BY ok.s LIMIT 1) n)"
    # kNN: others by (distance, index); extents over the nearest k; counts within them; harmonic sums
    psi = "(CASE WHEN {0} > 1 THEN list_sum(list_transform(range(1, CAST({0} AS BIGINT)), lambda j: 1.0::DOUBLE / j)) ELSE 0 END - 0.5772156649015329)"

    def knn(k: str, by: str, source: str) -> str:
        return f"""d AS (SELECT a.{by}, a.idx, b.idx AS i2, abs(b.x - a.x) AS ax, abs(b.y - a.y) AS ay, row_number() OVER (PARTITION BY a.{by}, a.idx ORDER BY greatest(abs(b.x - a.x), abs(b.y - a.y)), b.idx) AS rn FROM {source} a JOIN {source} b ON a.{by} = b.{by} AND a.idx <> b.idx),
        m AS (SELECT {by}, idx, k, max(ax) AS dx, max(ay) AS dy FROM d, {k} WHERE rn <= k GROUP BY ALL),
        q AS (SELECT m.{by}, m.idx, m.k, sum(CASE WHEN ax <= dx THEN 1 ELSE 0 END) AS nx, sum(CASE WHEN ay <= dy THEN 1 ELSE 0 END) AS ny, count(*) + 1 AS n FROM m JOIN d ON d.{by} = m.{by} AND d.idx = m.idx GROUP BY ALL),
        v AS (SELECT {by}, k, CAST(max(n) AS BIGINT) AS n, {psi.format('k')} - 1.0::DOUBLE / k - avg({psi.format('nx')} + {psi.format('ny')}) + {psi.format('max(n)')} AS mi FROM q GROUP BY {by}, k)"""

    fill = "f AS (SELECT CAST(unnest(range((SELECT min(idx) FROM h), (SELECT max(idx) + 1 FROM h))) AS BIGINT) AS idx), s AS (SELECT f.idx, {v}, last_value(CASE WHEN h.idx IS NOT NULL THEN h.idx END IGNORE NULLS) OVER a AS ia, first_value(h.idx IGNORE NULLS) OVER z AS ib{more} FROM f LEFT JOIN h ON f.idx = h.idx WINDOW a AS (ORDER BY f.idx ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), z AS (ORDER BY f.idx ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))"

    def line(c: str) -> str:
        return f"CASE WHEN {c} IS NOT NULL THEN {c} WHEN ia IS NULL THEN {c}b WHEN ib IS NULL THEN {c}a ELSE {c}a + ({c}b - {c}a) * (idx - ia) / (ib - ia) END"

    ends = lambda c: f", last_value(h.{c} IGNORE NULLS) OVER a AS {c}a, first_value(h.{c} IGNORE NULLS) OVER z AS {c}b"
    even = f"h AS ({ev}), {fill.format(v='h.x, h.y', more=ends('x') + ends('y'))}, p AS (SELECT idx, {line('x')} AS x, {line('y')} AS y FROM s)"
    steps = "z AS (SELECT *, sign(x - lag(x) OVER w) * sign(y - lag(y) OVER w) AS t FROM p WINDOW w AS (PARTITION BY pair_id ORDER BY idx)), u AS (SELECT pair_id, count(*) AS n, CAST(sum(CASE WHEN t > 0 THEN 1 ELSE 0 END) AS BIGINT) AS pp, CAST(sum(CASE WHEN t < 0 THEN 1 ELSE 0 END) AS BIGINT) AS np FROM z GROUP BY 1), r AS (SELECT *, (pp - np) / (n - 1) AS mu FROM u)"
    return {
        "overall_plugin_mi": f"{plug} SELECT pair_id, n, {cols('mi')} FROM j",
        "entropies": f"{plug} SELECT pair_id, {cols('hx', 'hy', 'hxy')} FROM j",
        "norm_mi": f"{plug} SELECT pair_id, {cols('h_norm', 'mi_norm1', 'mi_norm2')} FROM j",
        "categorical_mi": f"WITH b AS ({cat}), {info('b', 'pair_id')} SELECT pair_id, n, {cols('hx', 'hy', 'hxy', 'mi')} FROM j",
        "knn_mi_overall": f"WITH {p2}, ks AS (SELECT 6 AS k), {knn('ks', 'pair_id', 'p')} SELECT pair_id, n, {cols('mi')} FROM v",
        "knn_mi_windows": f"WITH {even}, pw AS (SELECT w.s AS s, idx, x, y FROM p JOIN (SELECT CAST(unnest(range((SELECT min(idx) FROM p), (SELECT max(idx) - 46 FROM p), 24)) AS BIGINT) AS s) w ON idx >= w.s AND idx < w.s + 48), ks AS (SELECT 6 AS k), {knn('ks', 's', 'pw')} SELECT s, s + 48 AS e, n, {cols('mi')} FROM v",
        "k_sweep": f"WITH p AS ({ev}), ks AS (SELECT CAST(range AS BIGINT) AS k FROM range(1, 21)), {knn('ks', 'pair_id', 'p')} SELECT k, {cols('mi')} FROM v",
        "direction": f"WITH {p4}, {steps} SELECT pair_id, n, pp, np, {cols('mu')}, CASE WHEN mu > 0 THEN 'positive' WHEN mu < 0 THEN 'negative' ELSE 'neither' END AS sign, (round(CASE WHEN mu > 0 THEN (pp - np) / pp WHEN mu < 0 THEN (np - pp) / np ELSE (n - 1 - pp - np) / (n - 1) END, 6) + 0.0) AS conf FROM r",
        "pearson_pairs": f"WITH {p4} SELECT pair_id, count(*) AS n, (round(corr(x, y), 6) + 0.0) AS pearson FROM p GROUP BY 1",
        "dcor_pairs": f"WITH {p2}, d AS (SELECT a.pair_id, a.idx AS i, b.idx AS j, abs(a.x - b.x) AS ax, abs(a.y - b.y) AS ay FROM p a JOIN p b ON a.pair_id = b.pair_id), c AS (SELECT pair_id, i, ax - avg(ax) OVER (PARTITION BY pair_id, i) - avg(ax) OVER (PARTITION BY pair_id, j) + avg(ax) OVER (PARTITION BY pair_id) AS u, ay - avg(ay) OVER (PARTITION BY pair_id, i) - avg(ay) OVER (PARTITION BY pair_id, j) + avg(ay) OVER (PARTITION BY pair_id) AS v FROM d) SELECT pair_id, count(DISTINCT i) AS n, (round(sqrt(greatest(sum(u * v), 0) / sqrt(sum(u * u) * sum(v * v))), 6) + 0.0) AS dcor FROM c GROUP BY 1",
        "resample_hour": f"SELECT {hour} AS idx, count(*) AS n, round(sum(value), 2) AS v FROM events GROUP BY 1",
        "stream_replay": f"SELECT {hour} AS idx, count(*) AS n, round(sum(value), 2) AS v FROM events GROUP BY 1",
        "interpolate": f"WITH h AS (SELECT CAST(floor(date_diff('minute', TIMESTAMP '2024-01-01', ts) / 15) AS BIGINT) AS idx, round(sum(value), 2) AS v FROM events GROUP BY 1), {fill.format(v='h.v', more=ends('v'))} SELECT idx, (round({line('v')}, 6) + 0.0) AS v, v IS NULL AS imputed FROM s",
        "pair_align": f"SELECT idx, x, y FROM ({users})",
        "grid_scores": f"WITH {win} SELECT s, e, n, {cols('hx', 'hy', 'hxy', 'mi', 'h_norm', 'mi_norm1', 'mi_norm2')} FROM j",
        "plugin_panes": f"WITH {win} SELECT s, n, {cols('mi')} FROM j",
        "layer_select": f"WITH RECURSIVE {passing}, {greedy} SELECT s, e FROM g",
        "leftout_segments": f"WITH RECURSIVE {passing}, {greedy}, x AS (SELECT coalesce(lag(e) OVER (ORDER BY s), (SELECT min(idx) FROM p)) AS s, s AS e FROM g UNION ALL SELECT coalesce((SELECT max(e) FROM g), (SELECT min(idx) FROM p)), (SELECT max(idx) + 1 FROM p)) SELECT s, e FROM x WHERE s < e",
        "merged_windows": f"WITH {passing}, k AS (SELECT s, e, CASE WHEN max(e) OVER (ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) > s THEN 0 ELSE 1 END AS f FROM ok), l AS (SELECT s, e, sum(f) OVER (ORDER BY s) AS i FROM k) SELECT min(s) AS s, max(e) AS e FROM l GROUP BY i",
        "coverage": f"WITH RECURSIVE {passing}, {greedy} SELECT 'EV_SUM' AS pair_id, (round(coalesce(sum(e - s), 0) / (SELECT max(idx) + 1 - min(idx) FROM p), 6) + 0.0) AS coverage FROM g",
        "sigma_sweep": f"WITH RECURSIVE {win}, sg AS (SELECT range / 20 AS sigma FROM range(4, 15)), ok AS (SELECT sigma, s, e FROM j, sg WHERE round(mi, 6) >= sigma), g AS (SELECT sigma, min(s) AS s, min(s) + 48 AS e FROM ok GROUP BY 1 UNION ALL SELECT g.sigma, n.s, n.e FROM g, LATERAL (SELECT ok.s, ok.e FROM ok WHERE ok.sigma = g.sigma AND ok.s >= g.e ORDER BY ok.s LIMIT 1) n) SELECT sigma, round(sum(e - s) / (SELECT max(idx) + 1 - min(idx) FROM p), 6) AS coverage FROM g GROUP BY 1",
        "two_step": f"WITH {win}, k AS (SELECT s, e, {cols('h_norm', 'mi_norm2')} FROM j) SELECT * FROM k WHERE h_norm >= 0.2 AND mi_norm2 >= 0.2",
        "topk_windows": f"WITH {win} SELECT s, e, n, {cols('mi', 'mi_norm2')} FROM j ORDER BY mi DESC, s LIMIT 11",
        "all_pairs_rank": f"WITH h AS (SELECT event_type AS var, {hour} AS idx, count(*) AS v FROM events GROUP BY ALL), s AS (SELECT n.var, CAST(r.range AS BIGINT) AS idx, CAST(coalesce(h.v, 0) AS DOUBLE) AS v FROM (SELECT DISTINCT var FROM h) n CROSS JOIN (SELECT unnest(range((SELECT min(idx) FROM h), (SELECT max(idx) + 1 FROM h))) AS range) r LEFT JOIN h ON h.var = n.var AND h.idx = r.range), p AS (SELECT a.var || '|' || b.var AS pair_id, a.idx, a.v AS x, b.v AS y FROM s a JOIN s b ON a.idx = b.idx AND a.var < b.var), b AS (SELECT pair_id, bx, b_y FROM ({bins('p')})), {info('b', 'pair_id')} SELECT pair_id, n, {cols('mi', 'hxy')} FROM j",
        "chunk_bounds": f"WITH p AS ({ev}), n AS (SELECT max(idx) + 1 AS n FROM p) SELECT CAST(r AS BIGINT) AS r, CAST(greatest(0, r * 336 - 168) AS BIGINT) AS s, CAST(least(n, (r + 1) * 336) AS BIGINT) AS e FROM n, (SELECT unnest(range(0, CAST(ceil((SELECT n FROM n) / 336.0) AS BIGINT))) AS r)",
    } | searched_sql(p4, ev, bins, info, cols)


def searched_sql(p4: str, ev: str, bins, info, cols) -> dict[str, str]:
    """SQL of what searches, streams and relations give."""
    pl, layers = f"{S.ranked()}, {S.related(SPANS, 'PL')}", [(x.size, x.step) for x in LADDER.layers]
    layered = S.search(pl, layers, "mi >= 0.6", f"pair_id, CAST(layer AS INT) AS layer, s, e, {cols('mi', 'mi_norm2')}, sign")
    line = f"{S.ranked()}, {S.related([(None, None, 'linear')], 'PL')}"
    four = f"{S.ranked(S.QUARTER)}, {S.related(FOUR, 'PL_FOUR')}"
    truth = ", ".join(f"({s}, {e}, '{k}')" for s, e, k in FOUR)
    tr = f"tr(ts, te, relation) AS (VALUES {truth})"
    day = "SELECT 'day' AS pair_id, idx // 24 AS idx, avg(x) AS x, avg(y) AS y FROM q GROUP BY 2"
    lags = " UNION ALL ".join(f"SELECT '{tau:+d}' AS pair_id, a.idx, a.x, b.y FROM q a JOIN q b ON a.idx = b.idx + {tau}" for tau in range(-3, 4))
    lags = lags.replace("+ -", "- ")
    rel = ", ".join(S.related([(None, None, k)], k, "rk", f"r{i}") for i, k in enumerate(synth.KINDS))
    rel = f"{S.ranked()}, {rel}, p AS ({' UNION ALL '.join(f'SELECT * FROM r{i}' for i in range(len(synth.KINDS)))})"
    centred = "{0} - avg({0}) OVER (PARTITION BY pair_id, i) - avg({0}) OVER (PARTITION BY pair_id, j) + avg({0}) OVER (PARTITION BY pair_id)"
    dcor = f"dd AS (SELECT a.pair_id, a.idx AS i, b.idx AS j, abs(a.x - b.x) AS ax, abs(a.y - b.y) AS ay FROM p a JOIN p b ON a.pair_id = b.pair_id), dc AS (SELECT pair_id, {centred.format('ax')} AS u, {centred.format('ay')} AS v FROM dd), de AS (SELECT pair_id, sqrt(greatest(sum(u * v), 0) / sqrt(sum(u * u) * sum(v * v))) AS dcor FROM dc GROUP BY 1)"
    best = "SELECT tr.s AS bs, tr.e AS be, w.s, w.e, (least(w.e, tr.e) - greatest(w.s, tr.s)) / (greatest(w.e, tr.e) - least(w.s, tr.s))::DOUBLE AS iou FROM tr JOIN fin w ON w.s < tr.e AND w.e > tr.s QUALIFY row_number() OVER (PARTITION BY tr.s ORDER BY iou DESC, w.s) = 1"
    spans = ", ".join(f"(CAST({s} AS BIGINT), CAST({e} AS BIGINT))" for s, e, _ in SPANS)
    recovered = S.search(pl, layers, "mi >= 0.6", "*").replace(" SELECT * FROM fin", f", tr(s, e) AS (VALUES {spans}), be AS ({best}) SELECT tr.s, tr.e, (round(coalesce(iou, 0), 6) + 0.0) AS iou, be.s - tr.s AS start_error, be.e - tr.e AS end_error FROM tr LEFT JOIN be ON tr.s = be.bs")
    kd = "kz AS (SELECT pair_id, idx, (x - avg(x) OVER w) / stddev_pop(x) OVER w AS x, (y - avg(y) OVER w) / stddev_pop(y) OVER w AS y, count(*) OVER w AS n FROM p WINDOW w AS (PARTITION BY pair_id)), kw AS (SELECT a.pair_id, a.idx, a.n, exp(-pow((a.x - b.x) / (1.06 * pow(a.n, -1.0::DOUBLE / 6)), 2) / 2) AS kx, exp(-pow((a.y - b.y) / (1.06 * pow(a.n, -1.0::DOUBLE / 6)), 2) / 2) AS ky FROM kz a JOIN kz b ON a.pair_id = b.pair_id AND a.idx <> b.idx), ks AS (SELECT pair_id, idx, n, sum(kx) AS fx, sum(ky) AS fy, sum(kx * ky) AS fxy FROM kw GROUP BY ALL)"
    avg_pair = ev.replace("EV_SUM", "EV_AVG").replace("round(sum(value), 2) AS y", f"{S.MEAN} AS y")
    norms = "nm(norm) AS (VALUES ('mi_norm1'), ('mi_norm2')), sg AS (SELECT norm, range / 20 AS sigma FROM nm, range(1, 20))"
    hits = "SELECT g.norm, g.sigma, g.s, max(CASE WHEN (least(g.e, te) - greatest(g.s, ts)) / (g.e - g.s) >= 0.5 THEN 1 ELSE 0 END) AS hit FROM g, tr GROUP BY ALL"
    effects = f"WITH RECURSIVE {four}, {S.windows([(120, 12)], 'p')}, {tr}, {norms}, ok AS (SELECT norm, sigma, s, e FROM sc, sg WHERE CASE WHEN norm = 'mi_norm1' THEN mi_norm1 ELSE mi_norm2 END >= sigma), g AS (SELECT * FROM (SELECT norm, sigma, min(s) AS s, min(e) AS e FROM ok GROUP BY ALL) UNION ALL SELECT n.* FROM g, LATERAL (SELECT * FROM ok WHERE ok.norm = g.norm AND ok.sigma = g.sigma AND ok.s >= g.e ORDER BY ok.s LIMIT 1) n), hi AS ({hits}) SELECT norm, sigma, count(s) AS total, CAST(coalesce(sum(hit), 0) AS BIGINT) AS meaningful FROM sg LEFT JOIN hi USING (norm, sigma) GROUP BY ALL"
    tiles = "CAST(ntile(6) OVER (PARTITION BY pair_id ORDER BY {0}, idx) AS INT)"
    change = "CAST(sign({0} - lag({0}) OVER (PARTITION BY pair_id ORDER BY idx)) AS INT)"
    own = lambda rows: f"WITH {rows}, b AS (SELECT pair_id, bx, b_y FROM ({bins('p')})), {info('b', 'pair_id')} SELECT pair_id, n, {cols('mi', 'hxy')} FROM j"
    two = lambda f, more: f"WITH {p4}, b AS (SELECT * FROM (SELECT pair_id, {f.format('x')} AS bx, {f.format('y')} AS b_y FROM p) {more}), {info('b', 'pair_id')} SELECT pair_id, n, {cols('mi', 'hxy')} FROM j"
    vars_ = f"SELECT 'n' AS var, idx, x AS v FROM e UNION ALL SELECT 'v', idx, y FROM e UNION ALL SELECT 't', CAST(date_diff('day', TIMESTAMP '1995-01-01', o_orderdate) AS BIGINT), round(sum(o_totalprice), 2) FROM orders GROUP BY 2"
    win = f"WITH RECURSIVE p AS ({ev}), b AS (SELECT w.g AS s, w.g + 48 AS e, bx, b_y FROM ({bins('p')}) q JOIN (SELECT CAST(unnest(range(0, (SELECT max(idx) - 46 FROM p), 12)) AS BIGINT) AS g) w ON q.idx >= w.g AND q.idx < w.g + 48), {info('b', 's, e')}, ok AS (SELECT s, e FROM j WHERE round(mi, 6) >= {SIGMA}), g AS (SELECT * FROM (SELECT s, e FROM ok ORDER BY s LIMIT 1) UNION ALL SELECT n.s, n.e FROM g, LATERAL (SELECT ok.s, ok.e FROM ok WHERE ok.s >= g.e ORDER BY ok.s LIMIT 1) n)"
    return {
        "layered_windows": layered,
        "layered_grid": layered,
        "layered_chunked": layered,
        "layered_recursive": layered,
        "layered_unfiltered": S.search(pl, layers, "mi >= 0.6", f"pair_id, CAST(layer AS INT) AS layer, s, e, {cols('mi', 'mi_norm2')}, sign", independent=True),
        "stream_search": S.search(pl, layers, "mi >= 0.6", f"pair_id, CAST(layer AS INT) AS layer, s, e, {cols('mi')}"),
        "planted_recovery": recovered,
        "threshold_effects": effects,
        "four_windows": S.search(four, [(120, 12), (60, 12)], "mi >= 0.6", "*").replace(" SELECT * FROM fin", f", {tr} SELECT CAST(layer AS INT) AS layer, s, e, {cols('mi')}, relation FROM fin LEFT JOIN tr ON ts < e AND te > s QUALIFY row_number() OVER (PARTITION BY layer, s ORDER BY least(e, te) - greatest(s, ts) DESC) = 1"),
        "exhaustive_windows": f"WITH {pl}, {S.windows([(24, 12), (36, 12), (48, 12)], 'p')} SELECT s, e, {cols('mi', 'mi_norm1')} FROM sc",
        "relation_scores": f"WITH {rel}, {S.neighbours('pair_id', 'p')}, pb AS (SELECT *, {S.bins_for(720)} AS bins FROM p), {S.entropies('pair_id', 'pb', 'CAST(greatest(3, round_even(sqrt(count(*) OVER w / 5.0::DOUBLE), 0)) AS INT)')}, {dcor}, li AS (SELECT pair_id, corr(x, y) AS pearson, covar_samp(x, y) AS covariance FROM p GROUP BY 1), fi AS (SELECT *, mi / hxy AS mi_norm2 FROM km JOIN he USING (pair_id) JOIN de USING (pair_id) JOIN li USING (pair_id)) SELECT pair_id, n, {cols('mi', 'mi_norm2', 'dcor', 'pearson', 'covariance')} FROM fi",
        "by_resolution": S.overall(f"{S.ranked()}, {S.related(SPANS, 'PL', 'rk', 'q')}, p AS (SELECT 'hour' AS pair_id, idx, x, y FROM q UNION ALL {day})", f"pair_id, n, {cols('mi', 'mu')}, sign"),
        "delays": f"WITH {S.ranked()}, {S.related([(None, None, 'linear')], 'PL', 'rk', 'q')}, p AS ({lags}), {S.neighbours('pair_id', 'p')} SELECT pair_id, n, {cols('mi')} FROM km",
        "knn_mi_distributed": f"WITH {line}, {S.neighbours('pair_id', 'p')} SELECT pair_id, {cols('mi')} FROM km",
        "kde_mi": f"WITH p AS ({ev} UNION ALL {avg_pair}), {kd}, kf AS (SELECT pair_id, n, avg(ln(greatest(fxy * (n - 1), 1e-300) / greatest(fx * fy, 1e-300))) AS mi FROM ks GROUP BY pair_id, n) SELECT pair_id, n, {cols('mi')} FROM kf",
        "frequency_mi": two(tiles, ""),
        "change_mi": two(change, "WHERE bx IS NOT NULL AND b_y IS NOT NULL"),
        "props_mi": own("p AS (SELECT 'k_value' AS pair_id, CAST(json_extract(props, '$.k') AS DOUBLE) AS x, value AS y FROM events WHERE json_extract(props, '$.k') IS NOT NULL)"),
        "embedding_mi": own("p AS (SELECT 'e0_e1' AS pair_id, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y FROM embeddings)"),
        "series_profile": f"WITH e AS ({ev}), s AS ({vars_}) SELECT var, count(v) AS n, max(idx) - min(idx) + 1 - count(v) AS missing, count(DISTINCT v) AS \"values\", {cols('low', 'high', 'mean').replace('round(low', 'round(min(v)').replace('round(high', 'round(max(v)').replace('round(mean', 'round(avg(v)')} FROM s GROUP BY var",
        "points_outside": f"{win} SELECT idx, EXISTS (SELECT 1 FROM g WHERE idx >= s AND idx < e) AS held FROM p",
        "stream_sliding": "WITH w AS (SELECT CAST(floor(date_diff('second', TIMESTAMP '2024-01-01', ts) / 43200.0) AS BIGINT) - k AS b, value AS x, CAST(user_id AS DOUBLE) AS y FROM events, (SELECT unnest([0, 1]) AS k)) SELECT b * 12 AS s, count(*) AS n, (round(corr(x, y), 6) + 0.0) AS pearson FROM w GROUP BY b",
        "stream_sessions": "WITH a AS (SELECT event_type, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 10 MINUTE THEN 0 ELSE 1 END AS f FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts)), b AS (SELECT event_type, ts, sum(f) OVER (PARTITION BY event_type ORDER BY ts ROWS UNBOUNDED PRECEDING) AS i FROM a) SELECT event_type, CAST(floor(epoch(min(ts))) AS BIGINT) AS since, count(*) AS n FROM b GROUP BY event_type, i",
    }
