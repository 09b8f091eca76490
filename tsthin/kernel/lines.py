"""Line-simplification baselines under the same exact check of the statistic: triangle areas, turning points, perceptual points."""

from __future__ import annotations

import numpy as np

from . import native, stats
from .greedy import Outcome, Rules, Series, certify, deviation_of, statistic_of, target


def _by_score(s: Series, score, removed: list[int], max_score: float = np.inf) -> None:
    """Remove points in order of their own score while the statistic's bound, the ratio and the score's bound allow."""
    rules, n = s.rules, len(s.x)
    if native.usable(n, rules):
        removed += native.thin_loop(s, rules.eps, 1, 1 + (area, sum_abs, mean_abs_err).index(score), max_score)[0]
        return
    value = np.full(n, np.inf)
    free = np.nonzero(s.alive & ~s.fixed)[0]
    value[free] = score(s, free)
    while True:
        if n / max(1, s.n_live) >= rules.ratio:
            break
        i = int(np.argmin(value))
        if not np.isfinite(value[i]) or value[i] > max_score:
            break
        sums = s.what_if(np.array([i]))[0]
        deviation = float(stats.distance(rules.distance, s.base, s.vector(sums)))
        if deviation > rules.eps:
            break
        l, r = s.left[i], s.right[i]
        s.commit(i, sums, deviation)
        removed.append(i)
        value[i] = np.inf
        near = np.array([p for p in (l, r) if 0 < p < n - 1 and not s.fixed[p]], dtype=int)
        if len(near):
            value[near] = score(s, near)


def area(s: Series, p: np.ndarray) -> np.ndarray:
    l, r = s.left[p], s.right[p]
    return np.abs((p - l) * (s.x[r] - s.x[l]) - (s.x[p] - s.x[l]) * (r - l)) / 2


def sum_abs(s: Series, p: np.ndarray) -> np.ndarray:
    return np.abs(s.x[p] - s.x[s.left[p]]) + np.abs(s.x[s.right[p]] - s.x[p])


def mean_abs_err(s: Series, p: np.ndarray) -> np.ndarray:
    _, change, seg, _ = s.redraw(p)
    return np.bincount(seg, np.abs(change), len(p)) / np.bincount(seg, minlength=len(p))


def triangle_area(x, rules: Rules, max_area: float = np.inf) -> tuple[np.ndarray, float]:
    x = np.asarray(x, float)
    if len(x) < 3:
        return np.arange(len(x)), 0.0
    s, removed = Series(x, rules), []
    _by_score(s, area, removed, max_area)
    return certify(x, Outcome(np.nonzero(s.alive)[0], removed, s.deviation), rules)


def turning(x: np.ndarray) -> np.ndarray:
    """Mask of changes of direction; on plateaus the last non-zero step counts. Ends are kept."""
    x = np.asarray(x, float)
    keep = np.zeros(len(x), bool)
    if len(x):
        keep[[0, -1]] = True
    step = np.sign(np.diff(x))
    idx = np.where(step != 0, np.arange(len(step)), -1)
    last = np.maximum.accumulate(idx) if len(step) else idx
    for i in range(1, len(x) - 1):
        if step[i] and last[i - 1] >= 0 and step[last[i - 1]] == -step[i]:
            keep[i] = True
    return keep


def turning_points(x, rules: Rules, score: str = "sum_abs") -> tuple[np.ndarray, float]:
    """Phase one keeps turning points only; phase two removes by score. If phase one breaks the bound, all points stay."""
    x = np.asarray(x, float)
    if len(x) < 3:
        return np.arange(len(x)), 0.0
    keep = turning(x)
    first = np.nonzero(keep)[0]
    if deviation_of(x, first, rules) > rules.eps:
        return np.arange(len(x)), 0.0
    drawn = np.interp(np.arange(len(x)), first, x[first])
    s = Series(drawn, rules, alive=keep, base=statistic_of(x, rules))
    removed: list[int] = []
    _by_score(s, {"sum_abs": sum_abs, "mean_abs_err": mean_abs_err}[score], removed)
    return certify(x, Outcome(np.nonzero(s.alive)[0], removed, s.deviation), rules)


def perceptual_points(x, rules: Rules, dist: str = "vertical", count: int | None = None) -> tuple[np.ndarray, float]:
    """Top down: insert the farthest point until the bound holds (or the ratio, or a count, is reached)."""
    x = np.asarray(x, float)
    n = len(x)
    if n < 3:
        return np.arange(n), 0.0
    base = statistic_of(x, rules)
    drawn = np.interp(np.arange(n), [0, n - 1], x[[0, -1]])
    keep = np.zeros(n, bool)
    keep[[0, -1]] = True
    limit = count if count is not None else n if np.isinf(rules.ratio) else max(2, int(np.ceil(n / rules.ratio)))
    to_bound = np.isinf(rules.ratio) and count is None
    if native.usable(n, rules):
        return _perceptual_long(x, rules, keep, base, limit, to_bound, dist)
    spans = {}

    def farthest(l, r):
        if r - l < 2:
            return
        t = np.arange(l + 1, r)
        if dist == "vertical":
            d = np.abs(x[t] - (x[l] + (x[r] - x[l]) * (t - l) / (r - l)))
        else:
            d = np.hypot(t - l, x[t] - x[l]) + np.hypot(r - t, x[r] - x[t])
        k = int(np.argmax(d))
        spans[l] = (float(d[k]), l + 1 + k, r)

    farthest(0, n - 1)
    deviation = float(stats.distance(rules.distance, base, statistic_of(drawn, rules)))
    while spans and keep.sum() < limit:
        if to_bound and deviation <= rules.eps:
            break
        l = max(spans, key=lambda q: (spans[q][0], -q))
        _, i, r = spans.pop(l)
        keep[i] = True
        drawn[l : i + 1] = np.linspace(x[l], x[i], i - l + 1)
        drawn[i : r + 1] = np.linspace(x[i], x[r], r - i + 1)
        farthest(l, i)
        farthest(i, r)
        deviation = float(stats.distance(rules.distance, base, statistic_of(drawn, rules)))
    return np.nonzero(keep)[0], deviation


def _perceptual_long(x, rules: Rules, keep: np.ndarray, base: np.ndarray, limit: int, to_bound: bool, dist: str) -> tuple[np.ndarray, float]:
    """The same with sums that follow each insertion; where they tell that the bound holds, it is checked from the drawn series."""
    centred, lags = x - x.mean(), np.array(rules.lags)
    while True:
        drawn = np.interp(np.arange(len(x)), np.nonzero(keep)[0], centred[keep])
        sums = stats.pair_sums(drawn, lags)
        deviation = float(stats.distance(rules.distance, base, stats.correlation(sums)))
        if keep.sum() >= min(limit, len(x)) or to_bound and deviation <= rules.eps:
            return np.nonzero(keep)[0], deviation
        found = native.insert_loop(centred, drawn, rules, keep, sums, base, limit, to_bound, dist == "euclidean")
        if found.sum() == keep.sum():
            return np.nonzero(keep)[0], deviation
        keep = found


def every_kth(n: int, k: int) -> np.ndarray:
    return np.unique(np.append(np.arange(0, n, k), n - 1)) if n else np.zeros(0, int)


def exhaustive(x, rules: Rules) -> tuple[np.ndarray, float]:
    """Fewest points within the bound by trying all subsets; for tests on at most 16 points."""
    x = np.asarray(x, float)
    n = len(x)
    if n > 16:
        raise ValueError("exhaustive search is for at most 16 points")
    best = (n, 0.0, np.arange(n))
    for mask in range(1 << max(0, n - 2)):
        inner = [i + 1 for i in range(n - 2) if mask >> i & 1]
        if len(inner) + 2 > best[0]:
            continue
        at = np.array([0, *inner, n - 1])
        d = deviation_of(x, at, rules)
        if d <= rules.eps and (len(at), d) < best[:2]:
            best = (len(at), d, at)
    return best[2], best[1]


def from_scratch(x, rules: Rules) -> tuple[np.ndarray, float]:
    """The greedy with every what-if rebuilt from nothing; the reference for tests."""
    x = np.asarray(x, float)
    kept = list(range(len(x)))
    d = 0.0
    while len(kept) > 2:
        tries = [(round(deviation_of(x, np.array(kept[:k] + kept[k + 1 :]), rules), 9), kept[k], k) for k in range(1, len(kept) - 1)]
        least, _, k = min(tries)
        if least > rules.eps or len(x) / len(kept) >= rules.ratio:
            break
        kept.pop(k)
        d = least
    return np.array(kept), d


__all__ = ["area", "every_kth", "exhaustive", "from_scratch", "perceptual_points", "target", "triangle_area", "turning", "turning_points"]
