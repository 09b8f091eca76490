"""Formulas against brute force, invariants of thinning, codecs."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from tsthin.kernel import codecs, lines, models, profile, stats
from tsthin.kernel.greedy import Rules, Series, deviation_of, target, thin_array, thin_at_bounds

walks = st.lists(st.floats(-50, 50).map(lambda v: round(v, 2)), min_size=3, max_size=40).map(lambda v: np.cumsum(v))


@pytest.mark.parametrize("window,agg", [(1, "mean"), (5, "mean"), (5, "sum"), (5, "max"), (4, "min")])
def test_updates_equal_rebuilt_sums(window, agg):
    rng = np.random.default_rng(3)
    s = Series(rng.normal(size=83), Rules(lags=(1, 2, 5, 7), window=window, agg=agg))
    for _ in range(60):
        live = np.nonzero(s.alive & ~s.fixed)[0]
        if not len(live):
            break
        what = s.what_if(live)
        for q, p in enumerate(live):
            pos, _, _, line = s.redraw(np.array([p]))
            y = s.x.copy()
            y[pos] = line
            assert np.allclose(stats.pair_sums(target(y, s.rules), s.lags), what[q], atol=1e-8)
        k = int(rng.integers(len(live)))
        s.commit(live[k], what[k], 0.0)


def test_partial_equals_linear_solve():
    r = stats.autocorr(np.cumsum(np.random.default_rng(0).normal(size=300)), range(1, 9))
    for k in range(1, 9):
        m = np.array([[1.0 if i == j else r[abs(i - j) - 1] for j in range(k)] for i in range(k)])
        assert np.isclose(np.linalg.solve(m, r[:k])[-1], stats.partial(r)[k - 1])


def test_long_lag_products_by_transform():
    x = np.random.default_rng(1).normal(size=500)
    a = stats.pair_sums(x, np.arange(1, 200))
    assert np.allclose(a[5], [x[: 500 - l] @ x[l:] for l in range(1, 200)])


@given(walks)
@settings(max_examples=40, deadline=None)
def test_invariants(x):
    rules = Rules(lags=(1, 2, 3), eps=0.05, hops="all")
    for kept, d in (thin_array(x, rules)[:2], lines.triangle_area(x, rules), lines.turning_points(x, rules), lines.perceptual_points(x, rules)):
        assert kept[0] == 0 and kept[-1] == len(x) - 1
        assert deviation_of(x, kept, rules) <= rules.eps + 1e-9
        assert len(set(kept.tolist())) == len(kept)


def test_greedy_equals_from_scratch_and_optimum_is_no_worse():
    rng = np.random.default_rng(5)
    for _ in range(6):
        x = np.round(np.cumsum(rng.normal(size=12)), 2)
        rules = Rules(lags=(1, 2, 3), eps=0.08, hops="all")
        kept, _, _ = thin_array(x, rules)
        assert kept.tolist() == lines.from_scratch(x, rules)[0].tolist()
        assert len(lines.exhaustive(x, rules)[0]) <= len(kept)


def test_ratio_and_edges():
    x = np.random.default_rng(2).normal(size=100)
    assert abs(len(thin_array(x, Rules(lags=(1, 2), ratio=4.0))[0]) - 25) <= 1
    assert thin_array(np.arange(50.0), Rules(lags=(1,), eps=1e-9))[0].tolist() == [0, 49]
    for n in range(3):
        assert len(thin_array(np.ones(n), Rules(lags=(1,), eps=0.1))[0]) == n
    assert thin_array(np.ones(20), Rules(lags=(1, 2), eps=0.1))[0].tolist() == [0, 19]
    pin = np.zeros(100, bool)
    pin[[7, 70]] = True
    kept = thin_array(x, Rules(lags=(1,), eps=0.5), pin)[0]
    assert {7, 70} <= set(kept.tolist())


@given(walks, st.floats(0.1, 20))
@settings(max_examples=40, deadline=None)
def test_piecewise_codecs_stay_within_tolerance(x, tol):
    for pieces in (codecs.pmc_mean(x, tol), codecs.swing(x, tol), codecs.merge_cones(codecs.cone_pieces(x, tol))[0]):
        assert sum(p[1] for p in pieces) == len(x)
        assert np.abs(codecs.draw(pieces, len(x)) - x).max() <= tol * (1 + 1e-9) + 1e-9


@given(st.lists(st.floats(allow_nan=True, allow_infinity=True, width=64), max_size=60))
@settings(max_examples=60, deadline=None)
def test_streams_round_trip_bit_by_bit(v):
    x = np.array(v, float)
    for enc, dec in ((codecs.xor_gorilla, codecs.xor_gorilla_decode), (codecs.xor_chimp, codecs.xor_chimp_decode)):
        payload, bits = enc(x)
        assert dec(payload, bits, len(x)).tobytes() == x.tobytes()


def test_fourier_keeps_all_and_energy():
    x = np.random.default_rng(0).normal(size=121)
    assert np.allclose(codecs.inverse_fourier(*codecs.fourier(x, 61), 121), x)
    f = np.fft.rfft(x)
    assert np.isclose((np.abs(f[0]) ** 2 + 2 * (np.abs(f[1:]) ** 2).sum()) / 121, (x * x).sum())


def test_profiles_agree():
    rng = np.random.default_rng(0)
    x = rng.normal(size=200)
    a, b = profile.profile_regular(x, 15)[0], profile.profile_pairs(x, 15, (0, 186))[0]
    assert np.allclose(a, b)
    kept = np.unique(np.append(rng.choice(200, 40, False), [0, 199]))
    y = np.interp(np.arange(200), kept, x[kept])
    assert np.allclose(profile.profile_irregular(kept, x[kept], 200, 15, (0, 186))[0], profile.profile_regular(y, 15)[0], atol=1e-6)


def test_models_follow_a_season():
    rng = np.random.default_rng(0)
    x = 10 + 5 * np.sin(2 * np.pi * np.arange(480) / 24) + rng.normal(0, 0.3, 480)
    for name in ("holt_winters", "dhr_arima", "stl_ets", "stl_arima", "lstm"):
        assert np.abs(models.MODELS[name](x[:-24], 24, 24) - x[-24:]).mean() < 2.5, name
    y, lam, shift = models.box_cox(x)
    assert np.allclose(models.inverse_box_cox(y, lam, shift), x)
    assert models.seasonal_strength(x, 24) > 0.6


def test_bounds_read_off_one_run():
    rng = np.random.default_rng(5)
    x = 10 * np.sin(np.arange(300) / 4) + rng.normal(size=300)
    for rules in (Rules(lags=(1, 2, 3, 7), hops="5log"), Rules(lags=(1, 2), window=4, hops="1"), Rules(lags=(1, 3), strict=True), Rules(lags=(1, 2), on_violation="skip")):
        for (kept, d), e in zip(thin_at_bounds(x, rules, (0.05, 1e-3, 0.01)), (0.05, 1e-3, 0.01)):
            want, dev, _ = thin_array(x, replace(rules, eps=e))
            assert kept.tolist() == want.tolist() and abs(d - dev) < 1e-12


def test_what_ifs_against_sums_from_scratch():
    rng = np.random.default_rng(6)
    for lags in ((1, 2, 3, 4, 5), (2, 9, 31), (1, 2, 3, 60)):
        s = Series(rng.normal(size=64), Rules(lags=lags))
        for i in (5, 6, 7, 8, 20, 60, 61):
            s.commit(i, s.what_if(np.array([i]))[0], 0.0)
        points = np.nonzero(s.alive & ~s.fixed)[0]
        for p, sums in zip(points, s.what_if(points)):
            kept = np.setdiff1d(np.nonzero(s.alive)[0], [p])
            drawn = np.interp(np.arange(64), kept, s.x[kept])
            assert np.allclose(sums, stats.pair_sums(drawn, np.array(lags)))
