"""Thinning of many series in common steps, and closed forms over wide gaps, against one series and one position at a time."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pytest

from tsthin.kernel import greedy
from tsthin.kernel.greedy import Rules, Series, thin_array, thin_arrays
from tsthin.operators import thinning


def _series():
    r = np.random.default_rng(3)
    xs = [np.round(r.exponential(50, int(n)), 2) for n in r.integers(1, 80, 60)]
    return [*xs, np.full(9, 3.0), np.cumsum(r.normal(size=300)), np.cumsum(r.normal(size=250))]


@pytest.mark.parametrize("more", [{"eps": 0.02}, {"eps": 0.05, "hops": "log", "distance": "rmse", "lags": (1, 3, 7)}, {"ratio": 3.0, "eps": np.inf}, {"eps": 0.02, "statistic": "partial"}, {"eps": 0.05, "strict": True, "distance": "chebyshev"}, {"eps": 0.02, "on_violation": "skip"}])
def test_many_series_as_one_by_one_in_far_fewer_steps(more, monkeypatch):
    rules, xs, calls = Rules(**({"lags": (1, 2, 3, 4, 5)} | more)), _series(), [0]
    plain = Series._what_if

    def counted(self, points):
        calls[0] += 1
        return plain(self, points)

    monkeypatch.setattr(Series, "_what_if", counted)
    want = [thin_array(x, rules) for x in xs]
    alone, calls[0] = calls[0], 0
    got = thin_arrays(xs, rules)
    for (k, d, c), (l, e, o) in zip(want, got):
        assert np.array_equal(k, l) and abs(d - e) < 1e-12 and c == o
    assert rules.on_violation == "skip" or calls[0] < alone / 2


def test_pins_side_by_side():
    xs = _series()
    pins = [np.arange(len(x)) % 5 == 2 for x in xs]
    for x, pin, (kept, _, _) in zip(xs, pins, thin_arrays(xs, Rules(lags=(1, 2), eps=0.5), pins)):
        assert np.array_equal(kept, thin_array(x, Rules(lags=(1, 2), eps=0.5), pin)[0]) and set(np.nonzero(pin)[0]) <= set(kept)


def test_series_cut_by_batches():
    xs = _series()
    rows = pd.concat([pd.DataFrame({"series_id": None if k == 4 else f"s{k:03d}", "pos": np.arange(len(x)), "value": x}) for k, x in enumerate(xs)], ignore_index=True)
    rules = Rules(lags=(1, 2, 3), eps=0.05)
    for size, points in ((7, 50), (1000, 65536), (11, 1)):
        got = pd.concat(thinning._runs((rows.iloc[i : i + size] for i in range(0, len(rows), size)), rules, None, points), ignore_index=True)
        want = pd.concat([rows.iloc[s : s + len(x)].iloc[thin_array(x, rules)[0]] for s, x in zip(np.cumsum([0, *[len(x) for x in xs[:-1]]]), xs)], ignore_index=True)
        assert got[["pos", "value"]].equals(want[["pos", "value"]]) and got["series_id"].fillna("").tolist() == want["series_id"].fillna("").tolist()


def test_few_bytes_are_dealt_over_all_cores(spark):
    s = spark.range(2000).selectExpr("CAST(id % 200 AS STRING) AS series_id", "id div 200 AS pos", "CAST(hash(id) % 100 AS DOUBLE) AS value")
    plan = thinning.thin_bounded(s, 0.1, (1, 2))._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(series_id#" in plan and "REPARTITION_BY_NUM" in plan


def test_wide_gaps_in_closed_form(monkeypatch):
    r = np.random.default_rng(1)
    x, alive = np.cumsum(r.normal(size=3000)) + 50, r.random(3000) < 0.04
    alive[[0, -1]] = True
    s = Series(np.interp(np.arange(3000), np.nonzero(alive)[0], x[alive]), Rules(lags=(1, 2, 5, 24)), alive=alive)
    points = np.nonzero(alive)[0][1:-1]
    points = points[s._inside(points)]
    want, got = s._what_if(points), s._wide_what_if(points)
    assert len(points) > 50 and np.abs(got - want).max() < 1e-12 * np.abs(want).max()
    rules = Rules(lags=tuple(range(1, 25)), eps=0.05, hops="log")
    kept, d = thin_array(x, rules)[:2]
    monkeypatch.setattr(greedy, "WIDE", np.inf)
    slow, e = thin_array(x, rules)[:2]
    assert np.array_equal(kept, slow) and d == e <= 0.05


def test_sweeps_run_a_task_for_each_series_and_method(spark):
    from tsthin.plans import workloads

    s = spark.range(400).selectExpr("'a' AS series_id", "id AS pos", "CAST(hash(id) % 100 AS DOUBLE) AS value")
    plan = workloads.sweep(s, ("greedy", "triangle_area"), (1e-2,))._jdf.queryExecution().executedPlan().toString()
    assert "REPARTITION_BY_NUM" in plan


def test_chunks_are_dealt_over_all_cores(spark, monkeypatch):
    from tsthin.operators import chunked

    plans, cut = [], chunked._cut
    monkeypatch.setattr(chunked, "_cut", lambda df: plans.append(df._jdf.queryExecution().executedPlan().toString()) or cut(df))
    s = spark.range(200).selectExpr("'a' AS series_id", "id AS pos", "CAST(hash(id) % 100 AS DOUBLE) AS value")
    kept = chunked.thin_chunked(s, Rules(lags=(1, 2), eps=0.05), chunk=50, max_rounds=1)
    assert 8 <= kept.count() < 200 and any("REPARTITION_BY_NUM" in p for p in plans)
