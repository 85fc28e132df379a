"""The experiment workloads one by one: natural pairs of the given tables scored whole, and planted pairs searched.

Natural pairs are scored as a whole and searched at several scales. A planted pair has x from a table and y a known function
of its rank inside given spans, and noise elsewhere, so that it is known what a search should find. All have SQL.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tempcorr import search_forms as S
from tempcorr.functions import measures as M
from tempcorr.operators import prep
from tempcorr.operators import windows as W
from tempcorr.oracle_forms import STEPS, bins, info, rounded
from tempcorr.plans import search
from tempcorr.sources import synth
from tempcorr.sources.tables import load
from tempcorr.workloads import hourly, pair, planted, r6

SCORED = {"k": 6, "tie": None}


def total(c: str) -> str:
    return f"round(sum({c}), 2)"


def mean(c: str) -> str:
    return f"round(round(sum({c}), 2) / count(*), 6)"


def kind(event: str) -> str:
    return f"count(CASE WHEN event_type = '{event}' THEN 1 END)"


def flagged(flag: str) -> str:
    return total(f"CASE WHEN l_returnflag = '{flag}' THEN l_extendedprice ELSE 0 END")


N = "count(*)"
#: (source, time column, unit, x, y) of each pair; Spark and DuckDB both read the expressions.
EVENTS, ORDERS, SHIPPED, JOINED = ("events", "ts", "hour"), ("orders", "o_orderdate", "day"), ("lineitem", "l_shipdate", "day"), ("joined", "o_orderdate", "day")
NATURAL = {
    "trips_speed": {"orders_speed": (*ORDERS, N, f"-{total('o_totalprice')}")},
    "fare_speed": {"events_value": (*EVENTS, N, total("value"))},
    "fare_duration": {"price_days": (*JOINED, mean("o_totalprice"), "round(sum({days}) / count(*), 6)")},
    "rain_casualties": {"shipped_discount": (*SHIPPED, N, mean("l_discount")), "shipped_tax": (*SHIPPED, N, mean("l_tax"))},
    "trips_collisions": {"click_error": (*EVENTS, kind("click"), kind("error"))},
    "collisions_complaints": {"error_signup": (*EVENTS, kind("error"), kind("signup"))},
    "production_irradiation": {"quantity_shipped": (*SHIPPED, total("l_quantity"), N), "quantity_price": (*SHIPPED, total("l_quantity"), total("l_extendedprice"))},
    "production_wind": {f"price_{f}": (*SHIPPED, flagged(f), N) for f in "ANR"},
    "weather_signs": {"humidity": (*ORDERS, N, f"-{total('o_totalprice')}"), "temperature": (*ORDERS, N, total("o_totalprice")), "humidity_temperature": (*ORDERS, f"-{total('o_totalprice')}", total("o_totalprice")), "pressure": (*ORDERS, N, f"-{mean('o_totalprice')}")},
    "production_estimate": {"price_net": (*SHIPPED, total("l_extendedprice"), "round(sum(l_extendedprice * (1 - l_discount)), 4)")},
    "pruned_pairs": {"orders_average": (*ORDERS, N, mean("o_totalprice")), "click_purchase": (*EVENTS, kind("click"), kind("purchase"))},
}
#: Workloads that are also scored in windows of so many steps each.
SPLIT = {"fare_speed": 24}
SINCE = {"hour": "2024-01-01", "day": "1995-01-01"}


#: Window sizes and steps of the searches: a week, two days, a day; 24, 12 and 4 weeks. A finer layer's step divides the
#: steps of coarser ones, so that all windows lie on one grid, as the SQL has them.
LADDERS = {"hour": ((168, 84), (48, 12), (24, 12)), "day": ((168, 84), (84, 28), (28, 14))}


def of_unit(name: str, unit: str | None = None) -> dict:
    return {p: v for p, v in NATURAL[name].items() if unit in (None, v[2])}


def rows_of(spark, d, pairs: dict) -> DataFrame:
    """(pair_id, idx, x, y) of natural pairs, on the steps that have rows."""
    out = None
    for p, (source, ts, unit, x, y) in pairs.items():
        rows = load(spark, d, "orders").join(load(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")) if source == "joined" else load(spark, d, source)
        days = "datediff(cast(l_shipdate AS date), cast(o_orderdate AS date))"
        idx = prep.index_of(F.col(ts), {"hour": "1H", "day": "1D"}[unit], SINCE[unit])
        got = rows.groupBy(idx.alias("idx")).agg(F.expr(x.replace("{days}", days)).cast("double").alias("x"), F.expr(y.replace("{days}", days)).cast("double").alias("y")).select(F.lit(p).alias("pair_id"), "idx", "x", "y")
        out = got if out is None else out.unionByName(got)
    return out


def rows_sql(pairs: dict) -> str:
    parts = []
    for p, (source, ts, unit, x, y) in pairs.items():
        table = "orders JOIN lineitem ON o_orderkey = l_orderkey" if source == "joined" else source
        days = "date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE))"
        idx = f"CAST(date_diff('{unit}', TIMESTAMP '{SINCE[unit]}', {ts}) AS BIGINT)"
        parts.append(f"SELECT '{p}' AS pair_id, {idx} AS idx, CAST({x.replace('{days}', days)} AS DOUBLE) AS x, CAST({y.replace('{days}', days)} AS DOUBLE) AS y FROM {table} GROUP BY ALL")
    return " UNION ALL ".join(parts)


def evened(rows: DataFrame) -> DataFrame:
    """Pairs without gaps, both variables interpolated."""
    s = [prep.even(rows.select(F.col("pair_id").alias("var"), "idx", F.col(c).alias("v"))).select(F.col("var").alias("pair_id"), "idx", F.col("v").alias(c)) for c in "xy"]
    return s[0].join(s[1], ["pair_id", "idx"])


def natural(name: str):
    """pair_id, n, mi, hxy, mi_norm2, mu, sign of each pair of a workload as a whole, by plug-in information."""

    def run(spark, d) -> DataFrame:
        out = rows_of(spark, d, of_unit(name))
        if name in SPLIT:
            out = out.unionByName(out.withColumn("pair_id", F.concat("pair_id", F.lit("/"), F.floor(F.col("idx") / SPLIT[name]).cast("string"))))
        scores = M.normalised(M.information(M.by_width(out, ["x", "y"], 6, ["pair_id"]), "b_x", "b_y", ["pair_id"]))
        return scores.join(M.directions(out, ["pair_id"]).select("pair_id", "mu", "sign"), "pair_id").select("pair_id", "n", r6("mi"), r6("hxy"), r6("mi_norm2"), r6("mu"), "sign")

    return run


def natural_sql(name: str) -> str:
    whole, head = rows_sql(of_unit(name)), ""
    if name in SPLIT:
        head = f"o AS ({whole}), "
        whole = f"SELECT * FROM o UNION ALL SELECT pair_id || '/' || CAST(idx // {SPLIT[name]} AS VARCHAR), idx, x, y FROM o"
    return f"WITH {head}p AS ({whole}), b AS (SELECT pair_id, bx, b_y FROM ({bins('p')})), {info('b', 'pair_id')}, {STEPS}, f AS (SELECT j.pair_id, j.n, mi, hxy, mi_norm2, mu FROM j JOIN r ON j.pair_id = r.pair_id) SELECT pair_id, n, {rounded('mi', 'hxy', 'mi_norm2', 'mu')}, CASE WHEN mu > 0 THEN 'positive' WHEN mu < 0 THEN 'negative' WHEN mu = 0 THEN 'neither' END AS sign FROM f"


def found_windows(name: str):
    """The windows of a workload's pairs, at all scales, that pass the two-step test by nearest-neighbour information."""

    def run(spark, d) -> DataFrame:
        out = None
        for unit, ladder in LADDERS.items():
            if of_unit(name, unit):
                got = search.layered_search(evened(rows_of(spark, d, of_unit(name, unit))), W.Ladder.of(*ladder), W.TwoStep(0.2, 0.2, "n2"))[0]
                out = got if out is None else out.unionByName(got)
        return shown(out)

    return run


def found_sql(name: str) -> str:
    parts = [S.search(f"raw AS ({rows_sql(of_unit(name, unit))}), {S.evened()}", ladder, "h_norm >= 0.2 AND mi_norm2 >= 0.2", S.SHOWN) for unit, ladder in LADDERS.items() if of_unit(name, unit)]
    return " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)


def views(spark, d, resolution: str, spans, name: str) -> DataFrame:
    """A planted pair over the counts of one event type, complete at a resolution."""
    counts = prep.extract(load(spark, d, "events"), prep.VariableSpec(name, "ts", F.count("*"), resolution, where=F.col("event_type") == "view"))
    return synth.plant(prep.even(counts, 0.0), spans)


def shown(found: DataFrame) -> DataFrame:
    return found.select("pair_id", "layer", "s", "e", r6("mi"), r6("mi_norm2"), r6("mu"), "sign")


def trips_wind(spark, d) -> DataFrame:
    """Two falls of one variable against another, searched by the hour and by the quarter; the best eleven windows of each."""
    spans, out = [(168, 336), (500, 548)], None
    for name, resolution, times in (("wind_1H", "1H", 1), ("wind_15M", "15M", 4)):
        p = views(spark, d, resolution, [(s * times, e * times, "negative") for s, e in spans], name)
        found = search.layered_search(p, W.Ladder.of((96 * times, 24 * times), (48 * times, 12 * times)), W.Absolute(0.5))[0]
        got = shown(W.rank(found, "mi", 11))
        out = got if out is None else out.unionByName(got)
    return out


def trips_rain(spark, d) -> DataFrame:
    """A pair related for two days only, and one that is flat but for a burst of seven samples, under both tests."""
    local = planted(spark, d, [(500, 548, "linear")], "local")
    burst = local.select(F.lit("burst").alias("pair_id"), "idx", F.when(F.col("idx").between(300, 306), F.col("idx") - 299.0).otherwise(0.0).alias("x"))
    both = local.unionByName(burst.withColumn("y", F.col("x") * 2))
    found = search.layered_search(both, W.Ladder.of((168, 24), (48, 12)), W.TwoStep(0.2, 0.2, "n2"))[0]
    whole = search.overall(search.untied(both), k=6, tie=None).withColumn("layer", F.lit(-1)).withColumn("s", F.lit(0).cast("long")).withColumn("e", F.col("n"))
    return shown(found).unionByName(shown(whole))


def fare_rain(spark, d) -> DataFrame:
    """A rise and a fall that the hours show and whole days do not."""
    p = planted(spark, d, [(168, 264, "linear"), (420, 468, "negative")], "by_hour")
    day = p.groupBy(F.floor(F.col("idx") / 24).alias("idx")).agg(F.avg("x").alias("x"), F.avg("y").alias("y")).select(F.lit("by_day").alias("pair_id"), "idx", "x", "y")
    found = search.layered_search(p, W.Ladder.of((96, 24), (48, 12)), W.Absolute(0.5))[0]
    whole = search.overall(search.untied(day), k=6, tie=None).withColumn("layer", F.lit(-1)).withColumn("s", F.lit(0).cast("long")).withColumn("e", F.col("n"))
    return shown(found).unionByName(shown(whole))


def trips_visibility(spark, d) -> DataFrame:
    """One rise of a week."""
    p = views(spark, d, "1H", [(168, 336, "linear")], "visibility")
    return shown(search.layered_search(p, W.Ladder.of((96, 24), (48, 12)), W.Absolute(0.5))[0])


def windows_of(p: DataFrame, *spans: tuple[int, int]) -> DataFrame:
    """The scores of given windows of every pair."""
    out = None
    for s, e in spans:
        wanted = W.whole(p).select("pair_id", F.lit(s).cast("long").alias("s"), F.lit(e).cast("long").alias("e"))
        got = search.score_windows(p, wanted, e - s, SCORED)
        out = got if out is None else out.unionByName(got)
    return out.select("s", "e", "n", r6("mi"), r6("mi_norm1"), r6("mi_norm2"))


def nested_core(spark, d) -> DataFrame:
    """An exact core inside a noisy span: both normalisations of either."""
    p = planted(spark, d, [(168, 336, "linear")], "nested")
    idx = F.col("idx")
    y = F.when((idx >= 200) & (idx < 224), F.col("x")).when((idx >= 168) & (idx < 336), F.col("x") + 0.5 * synth.noise(idx, "n")).otherwise(F.col("y"))
    return windows_of(p.withColumn("y", y), (200, 224), (168, 336))


def extreme_period(spark, d) -> DataFrame:
    """The period of an event against an ordinary one of the same length."""
    return windows_of(planted(spark, d, [(500, 548, "linear")], "extreme"), (500, 548), (100, 148))


def overall_local(spark, d) -> DataFrame:
    """A pair that is related over all its time, and one for two days only: scored whole, and the second one searched."""
    local = planted(spark, d, [(500, 548, "linear")], "local")
    whole = search.overall(search.untied(local.unionByName(pair(spark, d, "ORD_REV"))), k=6, tie=None).withColumn("layer", F.lit(-1)).withColumn("s", F.lit(0).cast("long")).withColumn("e", F.col("n"))
    found = search.layered_search(local, W.Ladder.of((168, 24), (48, 12), (24, 6)), W.Absolute(0.3))[0]
    return shown(whole).unionByName(shown(found))


SEARCHED = {"trips_wind": trips_wind, "trips_rain": trips_rain, "fare_rain": fare_rain, "trips_visibility": trips_visibility, "nested_core": nested_core, "extreme_period": extreme_period, "overall_local": overall_local}


def queries() -> dict:
    return {f"workload_{n}": natural(n) for n in NATURAL} | {f"windows_{n}": found_windows(n) for n in NATURAL} | {f"workload_{n}": f for n, f in SEARCHED.items()}


def hours(spans, name: str) -> str:
    return f"{S.ranked()}, {S.related(spans, name)}"


def searched_sql() -> dict[str, str]:
    """SQL of the planted workloads."""
    views_ = "WHERE event_type = 'view'"
    wind = []
    for name, idx, times in (("wind_1H", S.HOUR, 1), ("wind_15M", S.QUARTER, 4)):
        spans = [(s * times, e * times, "negative") for s, e in ((168, 336), (500, 548))]
        wind.append(S.search(f"{S.ranked(idx, 'count(*)', views_, True)}, {S.related(spans, name)}", [(96 * times, 24 * times), (48 * times, 12 * times)], "mi >= 0.5", S.SHOWN, top=11))
    local = [(500, 548, "linear")]
    whole = f"pair_id, -1 AS layer, CAST(0 AS BIGINT) AS s, n AS e, {rounded('mi', 'mi_norm2', 'mu')}, sign"
    burst = "SELECT 'burst' AS pair_id, idx, x, x * 2 AS y FROM (SELECT idx, CASE WHEN idx BETWEEN 300 AND 306 THEN idx - 299.0::DOUBLE ELSE 0.0::DOUBLE END AS x FROM rk)"
    rain = f"{S.ranked()}, {S.related(local, 'local', out='q')}, p AS (SELECT * FROM q UNION ALL {burst})"
    fare = [(168, 264, "linear"), (420, 468, "negative")]
    days = f"{S.ranked()}, {S.related(fare, 'by_hour', out='q')}, p AS (SELECT 'by_day' AS pair_id, idx // 24 AS idx, avg(x) AS x, avg(y) AS y FROM q GROUP BY 2)"
    nest = f"{S.ranked()}, {S.related([(168, 336, 'linear')], 'nested', out='q')}, p AS (SELECT pair_id, idx, x, CASE WHEN idx >= 200 AND idx < 224 THEN x WHEN idx >= 168 AND idx < 336 THEN x + 0.5 * {S.noise('n')} ELSE y END AS y FROM q)"
    two = f"{S.ranked()}, {S.related(local, 'local', out='q')}, p AS (SELECT * FROM q UNION ALL {rows_sql({'ORD_REV': (*ORDERS, N, total('o_totalprice'))})})"

    def given(series: str, *spans) -> str:
        wl = " UNION ALL ".join(f"SELECT pair_id, 0 AS layer, CAST({s} AS BIGINT) AS s, CAST({e} AS BIGINT) AS e, {S.bins_for(e - s)} AS bins, '{s}' AS w FROM (SELECT DISTINCT pair_id FROM p)" for s, e in spans)
        return f"WITH {series}, wl AS ({wl}), pw AS (SELECT w, idx, x, y, bins FROM p JOIN wl ON p.pair_id = wl.pair_id AND idx >= s AND idx < e), {S.neighbours('w', 'pw')}, {S.entropies('w', 'pw', 'bins')}, sc AS (SELECT s, e, n, mi, mi / log_n AS mi_norm1, mi / hxy AS mi_norm2 FROM wl JOIN km USING (w) JOIN he USING (w)) SELECT s, e, n, {rounded('mi', 'mi_norm1', 'mi_norm2')} FROM sc"

    both = lambda a, b: f"SELECT * FROM ({a}) UNION ALL SELECT * FROM ({b})"
    step = "h_norm >= 0.2 AND mi_norm2 >= 0.2"
    return {
        "trips_wind": both(*wind),
        "trips_rain": both(S.search(rain, [(168, 24), (48, 12)], step, S.SHOWN), S.overall(rain, whole)),
        "fare_rain": both(S.search(hours(fare, "by_hour"), [(96, 24), (48, 12)], "mi >= 0.5", S.SHOWN), S.overall(days, whole)),
        "trips_visibility": S.search(f"{S.ranked(S.HOUR, 'count(*)', views_, True)}, {S.related([(168, 336, 'linear')], 'visibility')}", [(96, 24), (48, 12)], "mi >= 0.5", S.SHOWN),
        "nested_core": given(nest, (200, 224), (168, 336)),
        "extreme_period": given(hours(local, "extreme"), (500, 548), (100, 148)),
        "overall_local": both(S.overall(two, whole), S.search(hours(local, "local"), [(168, 24), (48, 12), (24, 6)], "mi >= 0.3", S.SHOWN)),
    }


def oracle_sql() -> dict[str, str]:
    return {f"workload_{n}": natural_sql(n) for n in NATURAL} | {f"windows_{n}": found_sql(n) for n in NATURAL} | {f"workload_{n}": q for n, q in searched_sql().items()}
