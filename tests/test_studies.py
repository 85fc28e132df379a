"""The experiment workloads: natural pairs against SQL, planted pairs against their spans."""

import duckdb
import pytest

from tempcorr import studies


def rows(df):
    return [r.asDict() for r in df.collect()]


@pytest.mark.parametrize("name", list(studies.NATURAL))
def test_natural_pairs(spark, middle, name):
    got = {r["pair_id"]: r for r in rows(studies.queries()[f"workload_{name}"](spark, middle))}
    con = duckdb.connect()
    for t in ("events", "orders", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{middle}/{t}.parquet'")
    want = con.execute(studies.oracle_sql()[f"workload_{name}"]).df().set_index("pair_id").to_dict("index")
    assert set(got) == set(want)
    for p, w in want.items():
        assert (got[p]["n"], got[p]["sign"]) == (w["n"], w["sign"])
        assert all(got[p][c] == pytest.approx(w[c], abs=2e-6) for c in ("mi", "hxy", "mi_norm2", "mu"))


def test_strengths_and_signs(spark, middle):
    def of(name):
        return {r["pair_id"]: r for r in rows(studies.queries()[f"workload_{name}"](spark, middle))}

    assert of("trips_speed")["orders_speed"]["sign"] == "negative"
    signs = {p: r["sign"] for p, r in of("weather_signs").items()}
    assert (signs["humidity"], signs["temperature"], signs["humidity_temperature"]) == ("negative", "positive", "negative")
    assert of("production_estimate")["price_net"]["mi_norm2"] > 0.7
    assert all(r["mi_norm2"] < 0.2 for n in ("pruned_pairs", "rain_casualties", "collisions_complaints") for r in of(n).values())


def touches(r, s, e):
    return r["s"] < e and r["e"] > s


def test_planted_pairs(spark, middle):
    wind = rows(studies.trips_wind(spark, middle))
    for name, times in (("wind_1H", 1), ("wind_15M", 4)):
        best = max((r for r in wind if r["pair_id"] == name), key=lambda r: r["mi"])
        assert best["sign"] == "negative" and (touches(best, 168 * times, 336 * times) or touches(best, 500 * times, 548 * times))
    rain = rows(studies.trips_rain(spark, middle))
    assert any(r["pair_id"] == "local" and r["layer"] >= 0 and touches(r, 500, 548) for r in rain)
    assert not any(r["pair_id"] == "burst" and r["layer"] >= 0 for r in rain)
    fare = rows(studies.fare_rain(spark, middle))
    assert {r["sign"] for r in fare if r["layer"] >= 0 and touches(r, 168, 264)} == {"positive"}
    assert {r["sign"] for r in fare if r["layer"] >= 0 and touches(r, 420, 468)} == {"negative"}
    assert all(r["sign"] == "positive" for r in rows(studies.trips_visibility(spark, middle)) if touches(r, 192, 312))


def test_window_scores(spark, middle):
    core, span = sorted(rows(studies.nested_core(spark, middle)), key=lambda r: r["n"])
    assert core["mi_norm1"] > span["mi_norm1"]
    extreme, ordinary = sorted(rows(studies.extreme_period(spark, middle)), key=lambda r: -r["s"])
    assert extreme["mi"] > ordinary["mi"] + 0.5
    both = rows(studies.overall_local(spark, middle))
    whole = {r["pair_id"]: r["mi"] for r in both if r["layer"] == -1}
    assert whole["ORD_REV"] > 0.3 > whole["local"]
    assert any(r["layer"] >= 0 and touches(r, 500, 548) for r in both)


@pytest.mark.parametrize("name", ["windows_trips_speed", "windows_fare_speed", "workload_nested_core"])
def test_searches_equal_sql(spark, middle, name):
    con = duckdb.connect()
    for t in ("events", "orders", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{middle}/{t}.parquet'")
    found = studies.queries()[name](spark, middle)
    columns = sorted(found.columns)
    want = con.execute(f"SELECT {', '.join(columns)} FROM ({studies.oracle_sql()[name]})").fetchall()
    assert sorted(map(repr, want)) == sorted(repr(tuple(r)) for r in found.select(*columns).collect()) and want
