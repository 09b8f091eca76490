"""Compiled loops over long series against NumPy's."""

from __future__ import annotations

import numpy as np
import pytest

from tsthin.kernel import lines, native, stats
from tsthin.kernel.greedy import Rules, Series, thin, thin_array

pytestmark = pytest.mark.skipif(not native._works(), reason="no Java compiler here")


def _long():
    r = np.random.default_rng(1)
    return [np.cumsum(r.normal(size=6000)), 60 * np.sin(np.arange(6000) / 4) + r.normal(size=6000) * 20, np.tile(900 + np.arange(1000) / 10, 6), np.round(r.exponential(50, 5500), 2)]


RULES = [Rules(lags=tuple(range(1, 25)), eps=0.01, hops="5log"), Rules(lags=(1, 3, 24, 60), eps=1e-3, distance="rmse", hops="log"), Rules(lags=(1, 2), eps=0.02, on_violation="skip", distance="chebyshev", hops="log"), Rules(lags=(1, 7), distance="mape", ratio=4.0, hops="1")]


@pytest.mark.parametrize("rules", RULES)
def test_same_removals(rules, monkeypatch):
    for x in _long():
        found = []
        for least in (5000, 10**9):
            monkeypatch.setattr(native, "LONG", least)
            s = Series(x, rules)
            found.append((thin(s), s))
        (a, s), (b, t) = found
        assert a.removed == b.removed and a.counters == b.counters and np.allclose(a.path, b.path, atol=1e-10)
        assert np.allclose(s.x, t.x) and np.allclose(s.sums, t.sums) and s.n_live == t.n_live and np.array_equal(s.alive, t.alive)
        live = np.nonzero(s.alive)[0]
        assert np.array_equal(s.left[live[1:]], live[:-1]) and np.array_equal(s.right[live[:-1]], live[1:])


@pytest.mark.parametrize("run", [lines.triangle_area, lines.turning_points, lambda x, r: lines.turning_points(x, r, "mean_abs_err"), lines.perceptual_points, lambda x, r: lines.perceptual_points(x, r, "euclidean"), lambda x, r: lines.perceptual_points(x, r, count=10)])
def test_same_lines(run, monkeypatch):
    for x in _long():
        found = []
        for least in (5000, 10**9):
            monkeypatch.setattr(native, "LONG", least)
            found.append(run(x, Rules(lags=tuple(range(1, 25)), eps=0.05)))
        assert np.array_equal(found[0][0], found[1][0]) and abs(found[0][1] - found[1][1]) < 1e-9


def test_chunk_of_a_longer_series(monkeypatch):
    x = np.cumsum(np.random.default_rng(2).normal(size=9000))
    x -= x.mean()
    whole, rules, found = Series(x, Rules(lags=(1, 2, 7))), Rules(lags=(1, 2, 7), eps=1e-4, hops="log"), []
    for least in (5000, 10**9):
        monkeypatch.setattr(native, "LONG", least)
        s = Series(x[1993:8007], rules, 7, 6007, 1993, 9000, whole.sums, whole.base)
        found.append(thin(s, 1e-4).removed)
    assert found[0] == found[1] and len(found[0]) > 100


def test_long_series_take_no_step_in_numpy(monkeypatch):
    def never(self, points):
        raise AssertionError("a long series went through NumPy's loop")

    monkeypatch.setattr(Series, "_what_if", never)
    x = np.tile(900 + np.arange(1000) / 10, 60)
    assert len(thin_array(x, Rules(lags=tuple(range(1, 25)), eps=1e-3, hops="5log"))[0]) <= 120
    assert len(lines.triangle_area(x, Rules(lags=tuple(range(1, 25)), eps=1e-3))[0]) <= 120


def test_long_chunks_take_no_step_in_numpy(monkeypatch):
    def never(self, points):
        raise AssertionError("a long chunk went through NumPy's loop")

    x = np.cumsum(np.random.default_rng(3).normal(size=60_000))
    x -= x.mean()
    rules = Rules(lags=(1, 2, 3, 4, 5, 6, 7), eps=1e-4, hops="log")
    whole = Series(x, rules)
    monkeypatch.setattr(Series, "_what_if", never)
    s = Series(x[19_993:40_007], rules, 7, 20_007, 19_993, 60_000, whole.sums, whole.base)
    out = thin(s, 1e-5)
    assert len(out.removed) > 1000 and out.deviation <= 1e-5 and not s.fixed[out.removed].any()
    drawn = x.copy()
    drawn[19_993:40_007] = s.x
    assert np.allclose(stats.pair_sums(drawn, s.lags), s.sums, rtol=1e-9, atol=1e-3)
