"""DataFrame operators: golden facts, plans, edges."""

from __future__ import annotations

import numpy as np
import pytest
from conftest import MIDDLE, SMALL

from tsthin.kernel.greedy import Rules
from tsthin.operators import chunked, measures, reconstruct, series, thinning
from tsthin.sources import fixtures as fx


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_daily_series_golden(spark):
    k = thinning.thin_bounded(fx.day_sum(spark, MIDDLE), 0.05, (1, 2, 3), hops="all").orderBy("pos").collect()
    assert [r["pos"] for r in k] == [0, 2, 4, 5, 6, 8, 12, 14, 15, 16, 17, 18, 19, 20, 25, 26, 27, 28, 29]
    assert abs(k[0]["deviation"] - 0.0494744939) < 1e-9


def test_one_exchange_and_no_python_on_reconstruction(spark):
    s = spark.range(100).selectExpr("'a' AS series_id", "id AS pos", "CAST(id AS DOUBLE) AS value")
    p = plan(thinning.thin_bounded(s, 0.1, (1, 2)))
    assert p.count("Exchange") == 1
    p = plan(reconstruct.reconstruct(s))
    assert "Python" not in p and "Pandas" not in p and "Arrow" not in p


def test_filters_reach_the_scan(spark):
    from tsthin.plans.relational import QUERIES

    p = plan(QUERIES["scan_filtered_range"](spark, SMALL))
    assert "GreaterThanOrEqual(ts" in p and "ReadSchema: struct<event_id:bigint,ts:timestamp_ntz,value:double>" in p


def test_chunked_stays_within_the_bound(spark):
    s = fx.hour_runtotal(spark, MIDDLE)
    for chunk in (720, 180):
        k = chunked.thin_chunked(s, Rules(lags=tuple(range(1, 13)), eps=1e-3, hops="log"), chunk=chunk)
        r = measures.verify_bound(s, k.select("series_id", "pos", "value"), 1e-3, list(range(1, 13))).first()
        assert r["ends_kept"] and r["subset_ok"] and r["bound_ok"]
        assert k.count() < 720
    with pytest.raises(ValueError):
        chunked.thin_chunked(s, Rules(lags=(1, 50), eps=1e-3), chunk=20)


def test_dispatcher_sends_long_series_through_chunks(spark):
    s = fx.hour_runtotal(spark, MIDDLE).unionByName(fx.day_sum(spark, MIDDLE))
    k = thinning.thin_any(s, Rules(lags=(1, 2, 3), eps=0.01, hops="log"), max_points=500, chunk=180)
    assert {r["series_id"] for r in k.select("series_id").distinct().collect()} == {"hour_runtotal", "day_sum"}


def test_prefix_spread_against_brute_force():
    x = np.round(np.random.default_rng(0).normal(size=60), 1)
    want = [0.0] + [np.abs(x[:i] - x[:i].mean()).mean() for i in range(1, 60)]
    assert np.allclose(measures.prefix_spread(x), want)


def test_filling_and_missing(spark):
    s = spark.createDataFrame([("a", 0, None), ("a", 1, 2.0), ("a", 2, None), ("a", 3, 4.0), ("a", 4, None)], "series_id string, pos long, value double")
    got = [r["value"] for r in series.fill(s, "linear").orderBy("pos").collect()]
    assert got == [2.0, 2.0, 3.0, 4.0, 4.0]
    assert [r["value"] for r in series.fill(s, "ffill").orderBy("pos").collect()] == [None, 2.0, 2.0, 4.0, 4.0]
    with pytest.raises(Exception, match="missing"):
        thinning.thin_bounded(s, 0.1, (1,)).collect()
    with pytest.raises(Exception, match="missing"):
        series.fill(s, "error").collect()


def test_short_and_constant_series(spark):
    rows = [("one", 0, 1.0), ("two", 0, 1.0), ("two", 1, 5.0)] + [("flat", i, 3.0) for i in range(10)]
    s = spark.createDataFrame(rows, "series_id string, pos long, value double")
    got = {r["series_id"]: r["n_kept"] for r in thinning.meta(thinning.thin_bounded(s, 0.1, (1, 2))).collect()}
    assert got == {"one": 1, "two": 2, "flat": 2}
