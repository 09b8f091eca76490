"""Bottom-up thinning that keeps a statistic: the state of one series (or one chunk of it) and the greedy loop.

All what-ifs of one step are evaluated together: gaps of the candidates are concatenated, lagged neighbours read as rows
of one sliding window over the padded values, and contributions reduced by segment. Priorities live in one array whose
minimum is taken by a vector scan, which is faster here than a heap of boxed entries up to the chunk sizes used.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace

import numpy as np
from numpy.lib.stride_tricks import sliding_window_view

from . import native, stats


WIDE = 4  #: mean width of gaps from which on sums over them are replaced by closed forms


@dataclass
class Rules:
    """Parameters of one thinning run; names as in the public functions."""

    lags: tuple[int, ...] = (1,)
    eps: float = math.inf
    ratio: float = math.inf  #: stop once n over kept points reaches it
    statistic: str = "autocorr"
    distance: str = "mae"
    window: int = 1
    agg: str = "mean"
    hops: object = "10log"
    hops_at_lags: tuple[int, ...] = ()
    on_violation: str = "halt"
    give_up: int = 50
    strict: bool = False
    recheck: int = 256


def hop_count(hops, n: int, window: int = 1) -> int:
    """Hops to each side; named values are multiples of the natural logarithm of n, ``half`` and ``all``."""
    if hops == "all":
        return n
    if hops == "half":
        return max(1, n // 2)
    if isinstance(hops, str):
        hops = float(hops.removesuffix("log") or 1) * math.log(max(n, 2)) if hops.endswith("log") else float(hops)
    return min(n, max(1, round(float(hops) * window)))


class Series:
    """Current reconstruction of one series with live links, target values (the series or its windows) and pair sums.

    For a chunk of a longer series ``x`` holds a halo on both sides: ``lo`` and ``hi`` bound what may be removed,
    ``offset`` is the position of ``x[0]`` in the whole, ``total`` the whole length and ``sums`` the whole's pair sums.
    """

    def __init__(self, x, rules: Rules, lo: int = 0, hi: int | None = None, offset: int = 0, total: int | None = None, sums=None, base=None, pin=None, alive=None):
        self.rules, self.window = rules, max(1, rules.window)
        raw = np.asarray(x, dtype=float)
        self.center = float(raw.mean()) if len(raw) and sums is None else 0.0
        n = len(raw)
        self.lags = np.array([l for l in rules.lags], dtype=int)
        self.reach = int(self.lags.max()) if len(self.lags) else 0
        self.x = self._padded(raw - self.center, self.window == 1)
        self.lo, self.hi = lo, n if hi is None else hi
        self.offset, self.total = offset, total or n
        self.alive = np.ones(n, bool) if alive is None else np.asarray(alive, bool).copy()
        live = np.nonzero(self.alive)[0]
        self.left, self.right = np.full(n, -1), np.full(n, n)
        self.left[live[1:]], self.right[live[:-1]] = live[:-1], live[1:]
        self.fixed = np.zeros(n, bool)
        self.fixed[: self.lo + 1] = True
        self.fixed[max(0, self.hi - 1) :] = True
        if pin is not None:
            self.fixed |= np.asarray(pin, bool)
        self.n_live = int(self.alive[self.lo : self.hi].sum())
        k = self.window
        self.first_window = self.offset // k
        if k > 1:
            whole = (n // k) * k
            self.a = self._padded(self._aggregate(self.x[:whole].reshape(-1, k)), True)
            self.size = self.total // k
        else:
            self.a, self.size = self.x, self.total
        self.sums = stats.pair_sums(self.a, self.lags) if sums is None else np.array(sums, dtype=float)
        self.base = self.vector(self.sums) if base is None else np.asarray(base, dtype=float)
        self.deviation = float(stats.distance(rules.distance, self.base, self.vector(self.sums)))
        self.evaluated = self.redrawn = 0
        self.last = None

    def _padded(self, values: np.ndarray, lagged: bool) -> np.ndarray:
        """The values, as the middle of an array with zeros for the longest lag on both sides if lagged values are read."""
        if not lagged:
            return values
        whole = self.whole = np.zeros(len(values) + 2 * self.reach)
        inner = whole[self.reach : self.reach + len(values)]
        inner[:] = values
        self.around = sliding_window_view(whole, 2 * self.reach + 1)  # row j: the values from j - reach to j + reach
        return inner

    def _aggregate(self, w: np.ndarray) -> np.ndarray:
        return {"mean": w.mean, "sum": w.sum, "min": w.min, "max": w.max}[self.rules.agg](axis=-1)

    def vector(self, sums: np.ndarray) -> np.ndarray:
        r = stats.correlation(sums)
        if callable(self.rules.statistic):
            return self.rules.statistic(r)
        return stats.partial(r) if self.rules.statistic == "partial" else r

    def redraw(self, points: np.ndarray):
        """Positions strictly between the live neighbours of each point, their changes, and the segment each belongs to."""
        l, r = self.left[points], self.right[points]
        m = r - l - 1
        seg = np.repeat(np.arange(len(points)), m)
        step = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m) + 1
        pos = l[seg] + step
        line = self.x[l][seg] + (self.x[r] - self.x[l])[seg] * (step / (m + 1)[seg])
        return pos, line - self.x[pos], seg, line

    def _targets(self, pos, change, seg, line):
        """Changes of target values: ``(index, delta, segment)`` with local indices of windows (or points)."""
        k = self.window
        if k == 1:
            return pos, change, seg
        w = pos // k
        ok = w < len(self.a)
        pos, change, seg, line, w = pos[ok], change[ok], seg[ok], line[ok], w[ok]
        if not len(w):
            return w, change, seg
        new = np.ones(len(w), bool)
        new[1:] = (w[1:] != w[:-1]) | (seg[1:] != seg[:-1])
        at = np.nonzero(new)[0]
        if self.rules.agg in ("mean", "sum"):
            delta = np.add.reduceat(change, at) / (k if self.rules.agg == "mean" else 1)
        else:
            run = np.cumsum(new) - 1
            values = self.x[: len(self.a) * k].reshape(-1, k)[w[at]].copy()
            values[run, pos % k] = line
            delta = self._aggregate(values) - self.a[w[at]]
        return w[at], delta, seg[at]

    def what_if(self, points: np.ndarray) -> np.ndarray:
        """Pair sums if each point alone were removed: (points, 6, lags)."""
        out = np.empty((len(points), 6, len(self.lags)))
        budget = max(1, 400_000 // max(1, len(self.lags)))
        widths = self.right[points] - self.left[points] - 1
        if self.window == 1 and len(points) > 1 and widths.sum() > WIDE * len(points):
            wide = self._inside(points)
            if wide.sum() > 1 and self.right[points[wide]].max() - self.left[points[wide]].min() <= 4 * widths.sum() + 1000:
                out[wide] = self._wide_what_if(points[wide])
                if not wide.all():
                    out[~wide] = self._what_if(points[~wide])
                return out
        at = 0
        while at < len(points):
            to = at + max(1, int(np.searchsorted(np.cumsum(widths[at:]), budget)))
            out[at:to] = self._what_if(points[at:to])
            at = to
        return out

    def _inside(self, points: np.ndarray) -> np.ndarray:
        """Points whose gaps are at least the longest lag away from both ends of the whole, where every change is in all pairs."""
        return (self.left[points] + 1 + self.first_window >= self.reach) & (self.right[points] - 1 + self.first_window < self.size - self.reach)

    def _wide_what_if(self, points: np.ndarray) -> np.ndarray:
        """As ``_what_if`` at a cost that does not grow with gaps, but for two running sums over the stretch of all points.

        A removal changes its gap by a multiple of a tent, whose second difference has three terms. So the products of the
        tent and lagged values are three terms in the second running sum of the values, and those of the tent and itself
        are terms in the cube of distances between its corners.
        """
        l, r, reach, count = self.left[points], self.right[points], self.reach, len(self.lags)
        self.evaluated += len(points)
        self.redrawn += int((r - l - 1).sum())
        p, q = (points - l).astype(float), (r - points).astype(float)
        height = self.x[points] - self.x[l] - (self.x[r] - self.x[l]) * (p / (p + q))
        first = int(l.min())
        stretch = self.whole[first : int(r.max()) + 2 * reach + 1]
        level = stretch.mean()
        twice = np.concatenate([[0.0], np.cumsum(np.cumsum(stretch - level))])
        shift = np.concatenate([-self.lags, [0], self.lags]) + (reach - first)
        w = np.stack([1 / p, -(1 / p + 1 / q), 1 / q])
        met = sum(twice[c[:, None] + shift] * w[k][:, None] for k, c in enumerate((l, points, r))) + (level * (p + q) / 2)[:, None]
        lags = np.concatenate([[0], self.lags]).astype(float)
        own = 0.0
        for apart, weight in ((0 * p, (w * w).sum(0) / 2), (p, w[0] * w[1]), (q, w[1] * w[2]), (p + q, w[0] * w[2])):
            for m in (np.abs(lags - apart[:, None]), lags + apart[:, None]):
                own = own + (m * m * m - m) * (weight / 12)[:, None]
        own *= (height * height)[:, None]
        out = self._sums_of(points)
        out[:, 1:3] -= (height * (p + q) / 2)[:, None, None]
        out[:, 3:5] += (own[:, 0] - 2 * height * met[:, count])[:, None, None]
        out[:, 5] += own[:, 1:] - height[:, None] * (met[:, :count] + met[:, count + 1 :])
        return out

    def _sums_of(self, points: np.ndarray) -> np.ndarray:
        return np.broadcast_to(self.sums, (len(points), *self.sums.shape)).copy()

    def _base_of(self, points: np.ndarray) -> np.ndarray:
        return self.base

    def _place(self, j: np.ndarray):
        """Positions in the whole, and how many there are from each to its end."""
        g = j + self.first_window
        return g, self.size - g

    def _what_if(self, points: np.ndarray) -> np.ndarray:
        pos, change, seg, line = self.redraw(points)
        self.evaluated += len(points)
        self.redrawn += len(pos)
        j, d, seg = self._targets(pos, change, seg, line)
        out = self._sums_of(points)
        if len(points) == 1:
            self.last = (int(points[0]), pos, line, j, d)
        if not len(j):
            return out
        a, lags, reach = self.a, self.lags, self.reach
        start = np.nonzero(np.append(True, seg[1:] != seg[:-1]))[0]
        rows = seg[start]
        one = np.add.reduceat(np.stack([d, 2 * a[j] * d + d * d], 1), start)
        out[rows, 1:3] += one[:, :1, None]
        out[rows, 3:5] += one[:, 1:, None]
        g, rest = self._place(j)
        if len(g) and (g.min() < reach or rest.min() <= reach):  # positions near an end are in fewer pairs
            for row, at in ((1, np.nonzero(rest <= reach)[0]), (2, np.nonzero(g < reach)[0])):
                out_of = (rest[at, None] <= lags) if row == 1 else (g[at, None] < lags)
                np.subtract.at(out[:, row], seg[at], d[at, None] * out_of)
                np.subtract.at(out[:, row + 2], seg[at], (2 * a[j[at]] * d[at] + d[at] * d[at])[:, None] * out_of)
        # changes of the same segment ahead, behind zeros that end each segment
        ahead = np.zeros(len(d) + (len(start) + 1) * reach)
        at = np.arange(len(d)) + np.repeat(np.arange(len(start)), np.diff(np.append(start, len(d)))) * reach
        ahead[at] = d
        follow, around = sliding_window_view(ahead, reach + 1)[at], self.around[j]
        if reach == len(lags):  # all lags from one on
            cross = (around[:, reach + 1 :] + around[:, :reach][:, ::-1] + follow[:, 1:]) * d[:, None]
        else:
            cross = (around[:, reach + lags] + around[:, reach - lags] + follow[:, lags]) * d[:, None]
        out[rows, 5] += np.add.reduceat(cross, start)
        return out

    def impacts(self, points: np.ndarray) -> np.ndarray:
        """Deviation of the statistic if each point alone were removed; infinite for fixed and removed points."""
        out = np.full(len(points), np.inf)
        ok = self.alive[points] & ~self.fixed[points]
        if ok.any():
            out[ok] = stats.distance(self.rules.distance, self._base_of(points[ok]), self.vector(self.what_if(points[ok])))
        return out

    def commit(self, i: int, sums: np.ndarray, deviation: float):
        if self.last is None or self.last[0] != i:
            self._what_if(np.array([i]))
        _, pos, line, j, d = self.last
        self.last = None
        self.x[pos] = line
        if self.window > 1:
            self.a[j] += d
        self.alive[i] = False
        l, r = self.left[i], self.right[i]
        self.right[l], self.left[r] = r, l
        self.sums, self.deviation = sums, deviation
        self.n_live -= 1

    def neighbours(self, i: int, hops: int) -> np.ndarray:
        """Live points within so many hops of a removed point, and those one season away if asked for."""
        if hops >= self.n_live:
            return np.nonzero(self.alive & ~self.fixed)[0]
        found = []
        for side in (-1, 1):  # live points are found in growing slices around the point
            got, span = np.zeros(0, int), 2 * hops + 8
            while True:
                a, b = (max(self.lo, i - span), i) if side < 0 else (i + 1, min(self.hi, i + span + 1))
                got = np.nonzero(self.alive[a:b])[0] + a
                if len(got) >= hops or (a <= self.lo if side < 0 else b >= self.hi):
                    break
                span *= 4
            found.append(got[-hops:] if side < 0 else got[:hops])
        for lag in self.rules.hops_at_lags:
            for p in (i - lag, i + lag):
                if self.lo <= p < self.hi and self.alive[p]:
                    found.append(np.array([p]))
        out = np.unique(np.concatenate(found))
        return out[~self.fixed[out]]


@dataclass
class Outcome:
    kept: np.ndarray
    removed: list[int]
    deviation: float
    counters: dict = field(default_factory=dict)
    path: list[float] = field(default_factory=list)  #: the deviation after each removal


def thin(series: Series, budget: float | None = None) -> Outcome:
    """Greedy loop: remove the point of least impact while the bound (or the ratio) allows."""
    rules = series.rules
    eps = rules.eps if budget is None else budget
    n = series.hi - series.lo
    hops = hop_count(rules.hops, n, series.window)
    if native.usable(len(series.x), rules):
        removed, path, skipped = native.thin_loop(series, eps, hops)
        return _outcome(series, removed, skipped, hops, path)
    impact = np.full(len(series.x), np.inf)
    everyone = np.nonzero(series.alive & ~series.fixed)[0]
    everyone = everyone[(everyone >= series.lo) & (everyone < series.hi)]
    if len(everyone) and n >= 3:
        impact[everyone] = np.round(series.impacts(everyone), 9)
    removed: list[int] = []
    path: list[float] = []
    skipped = 0
    while True:
        if not np.isinf(rules.ratio) and n / max(1, series.n_live) >= rules.ratio:
            break
        i = int(np.argmin(impact)) if len(impact) else 0
        if not len(impact) or not np.isfinite(impact[i]):
            break
        sums = series.what_if(np.array([i]))[0]
        deviation = float(stats.distance(rules.distance, series.base, series.vector(sums)))
        if deviation > eps or (rules.strict and deviation >= eps):
            if rules.on_violation != "skip" or skipped >= rules.give_up:
                break
            skipped += 1
            impact[i] = np.inf
            continue
        series.commit(i, sums, deviation)
        removed.append(i)
        path.append(deviation)
        impact[i] = np.inf
        if rules.recheck and len(removed) % rules.recheck == 0 and series.total == len(series.x):
            series.sums = stats.pair_sums(series.a, series.lags)
        near = series.neighbours(i, hops)
        if len(near):
            impact[near] = np.round(series.impacts(near), 9)
    return _outcome(series, removed, skipped, hops, path)


def _outcome(series: Series, removed: list[int], skipped: int, hops: int, path: list[float]) -> Outcome:
    kept = np.nonzero(series.alive)[0]
    return Outcome(kept[(kept >= series.lo) & (kept < series.hi)], removed, series.deviation, {"evaluated": series.evaluated, "redrawn": series.redrawn, "skipped": skipped, "hops": hops}, path)


def certify(raw: np.ndarray, outcome: Outcome, rules: Rules) -> tuple[np.ndarray, float]:
    """Recompute the deviation from the raw series alone; take back last removals while the bound is broken."""
    kept, removed = set(outcome.kept.tolist()), list(outcome.removed)
    while True:
        at = np.array(sorted(kept))
        d = deviation_of(raw, at, rules)
        if d <= rules.eps * (1 + 1e-9) + 1e-12 or not removed:
            return at, d
        kept.add(removed.pop())


def target(x: np.ndarray, rules: Rules) -> np.ndarray:
    k = max(1, rules.window)
    if k == 1:
        return x
    w = x[: len(x) // k * k].reshape(-1, k)
    return {"mean": w.mean, "sum": w.sum, "min": w.min, "max": w.max}[rules.agg](axis=1)


def statistic_of(x: np.ndarray, rules: Rules) -> np.ndarray:
    r = stats.autocorr(target(np.asarray(x, float), rules), rules.lags)
    return rules.statistic(r) if callable(rules.statistic) else stats.partial(r) if rules.statistic == "partial" else r


def deviation_of(raw: np.ndarray, kept: np.ndarray, rules: Rules) -> float:
    raw = np.asarray(raw, float)
    drawn = np.interp(np.arange(len(raw)), kept, raw[kept]) if len(kept) else raw
    return float(stats.distance(rules.distance, statistic_of(raw, rules), statistic_of(drawn, rules)))


def thin_array(x, rules: Rules, pin=None) -> tuple[np.ndarray, float, dict]:
    """Kept positions, certified deviation and counters of one whole series."""
    x = np.asarray(x, dtype=float)
    if len(x) < 3:
        return np.arange(len(x)), 0.0, {}
    s = Series(x, rules, pin=pin)
    out = thin(s)
    if np.isinf(rules.eps):
        return out.kept, deviation_of(x, out.kept, rules), out.counters
    kept, d = certify(x, out, rules)
    return kept, d, out.counters


def thin_at_bounds(x, rules: Rules, bounds) -> list[tuple[np.ndarray, float]]:
    """Kept positions and certified deviation under each bound, as ``thin_array`` gives them, from one run to the loosest.

    The order of removals does not depend on the bound, so the run to a tighter one is its part before the first breach.
    """
    x = np.asarray(x, dtype=float)
    if rules.on_violation != "halt":
        return [thin_array(x, replace(rules, eps=e))[:2] for e in bounds]
    if len(x) < 3:
        return [(np.arange(len(x)), 0.0) for _ in bounds]
    out, found = thin(Series(x, replace(rules, eps=max(bounds)))), []
    for e in bounds:
        to = next((k for k, d in enumerate(out.path) if d > e or (rules.strict and d >= e)), len(out.path))
        kept = np.setdiff1d(np.arange(len(x)), out.removed[:to])
        found.append(certify(x, Outcome(kept, out.removed[:to], out.path[to - 1] if to else 0.0), replace(rules, eps=e)))
    return found


class Together(Series):
    """Many series of similar lengths side by side, for removals from all of them in the same step.

    Rows of equal width with zeros behind each, so that lagged values of one series never reach into another.
    """

    def __init__(self, xs: list[np.ndarray], rules: Rules, pins: list | None = None):
        self.rules, self.window, self.last = rules, 1, None
        self.lags = np.array(rules.lags, dtype=int)
        self.reach = int(self.lags.max())
        self.lengths = np.array([len(x) for x in xs])
        rows, self.width = len(xs), int(self.lengths.max()) + self.reach
        self.a = self.x = self._padded(np.zeros(rows * self.width), True)
        self.alive, self.fixed = np.zeros((2, rows * self.width), bool)
        table, alive, fixed = (v.reshape(rows, -1) for v in (self.x, self.alive, self.fixed))
        for k, x in enumerate(xs):
            table[k, : len(x)] = x - x.mean()
            alive[k, : len(x)] = True
            fixed[k, [0, len(x) - 1]] = True
            if pins is not None:
                fixed[k, : len(x)] |= pins[k]
        at = np.arange(rows * self.width)
        self.left, self.right = at - 1, at + 1
        self.sums = np.stack([stats.pair_sums(table[k, :n], self.lags) for k, n in enumerate(self.lengths)])
        self.base = self.vector(self.sums)
        self.evaluated = self.redrawn = 0
        self.work = np.zeros((2, rows))

    def _inside(self, points):
        g, rest = self._place(points)
        return (g - points + self.left[points] + 1 >= self.reach) & (rest - self.right[points] + points >= self.reach)

    def _sums_of(self, points):
        return self.sums[points // self.width]

    def _base_of(self, points):
        return self.base[points // self.width]

    def _place(self, j):
        g = j % self.width
        return g, self.lengths[j // self.width] - g

    def what_if(self, points):
        row = points // self.width
        self.work[0] += np.bincount(row, minlength=len(self.lengths))
        self.work[1] += np.bincount(row, self.right[points] - self.left[points] - 1, len(self.lengths))
        return super().what_if(points)

    def commit_all(self, points: np.ndarray, sums: np.ndarray):
        pos, _, _, line = self.redraw(points)
        self.x[pos] = line
        self.alive[points] = False
        l, r = self.left[points], self.right[points]
        self.right[l], self.left[r] = r, l
        self.sums[points // self.width] = sums


def together(rules: Rules) -> bool:
    """Whether runs under these rules can go side by side."""
    return (
        rules.window <= 1 and rules.statistic in ("autocorr", "partial") and rules.distance in ("mae", "rmse", "chebyshev", "mape")
        and rules.on_violation == "halt" and not rules.hops_at_lags and len(rules.lags) > 0
    )


def thin_arrays(xs: list, rules: Rules, pins: list | None = None, cells: int = 32_768) -> list[tuple[np.ndarray, float, dict]]:
    """``thin_array`` of many series, those of similar lengths side by side in tables of at most so many cells."""
    xs = [np.asarray(x, dtype=float) for x in xs]
    out: list = [None] * len(xs)
    order = [k for k in np.argsort([len(x) for x in xs], kind="stable")[::-1] if len(xs[k]) >= 3] if together(rules) else []
    at = 0
    while at < len(order):
        width = len(xs[order[at]]) + max(rules.lags)
        some = [k for k in order[at : at + max(1, cells // width)] if 2 * len(xs[k]) >= len(xs[order[at]])]
        at += len(some)
        if len(some) > 1:
            for k, found in zip(some, _thin_table([xs[k] for k in some], rules, [pins[k] for k in some] if pins else None)):
                out[k] = found
    return [thin_array(x, rules, pins[k] if pins else None) if out[k] is None else out[k] for k, x in enumerate(xs)]


def _thin_table(xs, rules: Rules, pins) -> list[tuple[np.ndarray, float, dict]]:
    """The loop of ``thin`` with one removal from every series that still runs in each step."""
    t = Together(xs, rules, pins)
    rows, width = len(xs), t.width
    hops = np.array([hop_count(rules.hops, len(x)) for x in xs])
    impact = np.full(rows * width, np.inf)
    everyone = np.nonzero(t.alive & ~t.fixed)[0]
    if len(everyone):
        impact[everyone] = np.round(t.impacts(everyone), 9)
    turn = np.full(rows * width, -1)
    alive, fixed, by_row = t.alive.reshape(rows, width), t.fixed.reshape(rows, width), impact.reshape(rows, width)
    on, live, step = np.arange(rows), t.lengths.copy(), 0
    while True:
        if not np.isinf(rules.ratio):
            on = on[t.lengths[on] / live[on] < rules.ratio]
        i = on * width + by_row[on].argmin(1)
        i = i[np.isfinite(impact[i])]
        if not len(i):
            break
        sums = t.what_if(i)
        d = stats.distance(rules.distance, t._base_of(i), t.vector(sums))
        good = (d < rules.eps) if rules.strict else ~(d > rules.eps)
        i, sums = i[good], sums[good]
        on = i // width
        if not len(i):
            break
        t.commit_all(i, sums)
        impact[i], turn[i] = np.inf, step
        live[on] -= 1
        step += 1
        if rules.recheck and step % rules.recheck == 0:
            for k in on:
                t.sums[k] = stats.pair_sums(t.x[k * width : k * width + t.lengths[k]], t.lags)
        rank = np.cumsum(alive[on], axis=1, dtype=np.int32)
        here = np.take_along_axis(rank, (i % width)[:, None], 1)
        near = alive[on] & ~fixed[on] & (rank > here - hops[on, None]) & (rank <= here + hops[on, None])
        row, col = np.nonzero(near)
        points = on[row] * width + col
        if len(points):
            impact[points] = np.round(t.impacts(points), 9)
    found = []
    for k, x in enumerate(xs):
        of = turn[k * width : k * width + len(x)]
        gone = np.nonzero(of >= 0)[0]
        gone = gone[np.argsort(of[gone])].tolist()
        kept, counters = np.nonzero(of < 0)[0], {"evaluated": int(t.work[0, k]), "redrawn": int(t.work[1, k]), "skipped": 0, "hops": int(hops[k])}
        if np.isinf(rules.eps):
            found.append((kept, deviation_of(x, kept, rules), counters))
        else:
            found.append((*certify(x, Outcome(kept, gone, 0.0), rules), counters))
    return found
