"""Segment profiles (distance of each segment to its nearest other one) on regular and on kept form."""

from __future__ import annotations

import numpy as np


def profile_regular(x, m: int, rows: tuple[int, int] | None = None, normalise: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Least distance and nearest start for starts in ``rows``; starts closer than ``m`` do not count. By diagonals of lagged differences."""
    x = np.asarray(x, float)
    n = len(x) - m + 1
    lo, hi = rows or (0, n)
    best, where = np.full(max(0, hi - lo), np.inf), np.full(max(0, hi - lo), -1)
    if normalise and n > 0:
        c1, c2 = np.concatenate([[0.0], np.cumsum(x)]), np.concatenate([[0.0], np.cumsum(x * x)])
        mu = (c1[m:] - c1[:-m]) / m
        sd = np.sqrt(np.maximum((c2[m:] - c2[:-m]) / m - mu * mu, 1e-12))
    for lag in range(m, n):
        # pairs (i, i + lag) with i or i + lag in rows
        a, b = max(0, lo - lag), min(hi, n - lag)
        if b <= a:
            continue
        u, v = x[a : b + m - 1], x[a + lag : b + lag + m - 1]
        if normalise:
            c = np.concatenate([[0.0], np.cumsum(u * v)])
            r = ((c[m:] - c[:-m]) / m - mu[a:b] * mu[a + lag : b + lag]) / (sd[a:b] * sd[a + lag : b + lag])
            d = np.sqrt(np.maximum(2 * m * (1 - r), 0))
        else:
            c = np.concatenate([[0.0], np.cumsum((u - v) ** 2)])
            d = np.sqrt(np.maximum(c[m:] - c[:-m], 0))
        i = np.arange(a, b)
        for at, other in ((i, i + lag), (i + lag, i)):
            ok = (at >= lo) & (at < hi)
            k = at[ok] - lo
            better = d[ok] < best[k]
            best[k[better]], where[k[better]] = d[ok][better], other[ok][better]
    return best, where


def profile_pairs(x, m: int, rows: tuple[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """The same by comparing all pairs of segments directly, O(m) each: the plain baseline."""
    x = np.asarray(x, float)
    s = np.lib.stride_tricks.sliding_window_view(x, m)
    best, where = [], []
    for i in range(*rows):
        d = ((s - s[i]) ** 2).sum(1)
        d[max(0, i - m + 1) : i + m] = np.inf
        k = int(np.argmin(d))
        best.append(np.sqrt(d[k]))
        where.append(k if np.isfinite(d[k]) else -1)
    return np.array(best), np.array(where)


def profile_irregular(pos, value, n: int, m: int, rows: tuple[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """Exact profile from kept points alone: between consecutive breakpoints of either segment the difference is a line, whose squares sum in closed form."""
    pos, value = np.asarray(pos, int), np.asarray(value, float)
    total = n - m + 1
    lo, hi = rows
    best, where = np.full(hi - lo, np.inf), np.full(hi - lo, -1)

    def at(p):
        k = np.clip(np.searchsorted(pos, p, side="right") - 1, 0, max(0, len(pos) - 2))
        span = pos[k + 1] - pos[k] if len(pos) > 1 else np.ones_like(k)
        slope = (value[k + 1] - value[k]) / span if len(pos) > 1 else np.zeros(len(k))
        return value[k] + slope * (p - pos[k]), slope

    for lag in range(m, total):
        a, b = max(0, lo - lag), min(hi, total - lag)
        if b <= a:
            continue
        # breakpoints of x(t) and x(t + lag) over t in [a, b + m - 1)
        end = b + m - 1
        cuts = np.concatenate([[a], pos[(pos > a) & (pos < end)], pos[(pos - lag > a) & (pos - lag < end)] - lag, [end]])
        cuts = np.unique(cuts)
        t = cuts[:-1]
        (u, su), (v, sv) = at(t), at(t + lag)
        d0, s = u - v, su - sv
        q = np.diff(cuts).astype(float)
        part = lambda q: q * d0 * d0 + s * d0 * q * (q - 1) + s * s * q * (q - 1) * (2 * q - 1) / 6
        whole = np.concatenate([[0.0], np.cumsum(part(q))])

        def upto(p):
            k = np.clip(np.searchsorted(cuts, p, side="right") - 1, 0, len(t) - 1)
            w = (p - cuts[k]).astype(float)
            return whole[k] + w * d0[k] * d0[k] + s[k] * d0[k] * w * (w - 1) + s[k] * s[k] * w * (w - 1) * (2 * w - 1) / 6

        i = np.arange(a, b)
        d = np.sqrt(np.maximum(upto(i + m) - upto(i), 0))
        for one, other in ((i, i + lag), (i + lag, i)):
            ok = (one >= lo) & (one < hi)
            k = one[ok] - lo
            better = d[ok] < best[k]
            best[k[better]], where[k[better]] = d[ok][better], other[ok][better]
    return best, where


def discord(x, lengths=range(75, 126), normalise: bool = False, scaled: bool = True) -> tuple[int, int, float]:
    """Start, length and distance of the segment farthest from its nearest other one, over all lengths (distances over the root of the length)."""
    top = (-1, 0, -1.0)
    for m in lengths:
        if len(x) < 2 * m:
            continue
        d, _ = profile_regular(x, m, None, normalise)
        d = np.where(np.isfinite(d), d, -1)
        k = int(np.argmax(d))
        v = float(d[k]) / (np.sqrt(m) if scaled else 1)
        if v > top[2]:
            top = (k, m, v)
    return top
