"""Pair sums, correlation statistics and distances between statistic vectors."""

from __future__ import annotations

import numpy as np


def pair_sums(a: np.ndarray, lags: np.ndarray) -> np.ndarray:
    """Per lag: pairs, early sum, late sum, early and late sums of squares, sum of products. Shape (6, lags)."""
    n = len(a)
    c1, c2 = np.concatenate([[0.0], np.cumsum(a)]), np.concatenate([[0.0], np.cumsum(a * a)])
    early, late = np.clip(n - lags, 0, None), np.minimum(lags, n)
    if len(lags) > 8 * max(1.0, np.log2(n + 1)):
        size = 1 << int(np.ceil(np.log2(2 * n + 1)))
        f = np.fft.rfft(a, size)
        product = np.fft.irfft(f * np.conj(f), size)[np.minimum(lags, n)]
    else:
        product = np.array([a[: n - l] @ a[l:] if l < n else 0.0 for l in lags])
    return np.array([early.astype(float), c1[early], c1[-1] - c1[late], c2[early], c2[-1] - c2[late], product])


def correlation(sums: np.ndarray) -> np.ndarray:
    """Lagged-pair autocorrelation from pair sums of shape (..., 6, lags); NaN where a variance is zero."""
    m, x, y, xx, yy, xy = np.moveaxis(sums, -2, 0)
    mx, my = m * xx, m * yy
    vx, vy = mx - x * x, my - y * y
    floor = 1e-12
    good = (vx > floor * np.maximum(mx, 1e-300)) & (vy > floor * np.maximum(my, 1e-300)) & (m >= 2)
    cov = m * xy - x * y
    if good.all():
        return cov / np.sqrt(vx * vy)
    return np.where(good, cov / np.sqrt(np.where(good, vx * vy, 1.0)), np.nan)


def autocorr(a: np.ndarray, lags, form: str = "pairs") -> np.ndarray:
    """``pairs``: Pearson correlation of the n-l pairs. ``global``: one mean and variance, product averaged over n-l pairs."""
    lags = np.asarray(lags, dtype=int)
    a = np.asarray(a, dtype=float)
    if form == "pairs":
        return correlation(pair_sums(a - a.mean(), lags)) if len(a) else np.full(len(lags), np.nan)
    c = a - a.mean()
    var = (c * c).mean()
    return np.array([(c[: len(c) - l] @ c[l:]) / (len(c) - l) / var if l < len(c) and var > 0 else np.nan for l in lags])


def partial(r: np.ndarray) -> np.ndarray:
    """Partial autocorrelation at lags 1..L from autocorrelation (..., L), by the order recursion, for all rows at once."""
    r = np.asarray(r, dtype=float)
    rows = r.reshape(-1, r.shape[-1])
    out, phi = np.empty_like(rows), np.zeros_like(rows)
    with np.errstate(invalid="ignore", divide="ignore"):
        for k in range(rows.shape[1]):
            if k == 0:
                p = rows[:, 0]
            else:
                p = (rows[:, k] - (phi[:, :k] * rows[:, k - 1 :: -1][:, :k]).sum(1)) / (1 - (phi[:, :k] * rows[:, :k]).sum(1))
                phi[:, :k] = phi[:, :k] - p[:, None] * phi[:, k - 1 :: -1][:, :k]
            phi[:, k] = out[:, k] = p
    return out.reshape(r.shape)


def distance(kind: str, base: np.ndarray, other: np.ndarray) -> np.ndarray:
    """Distance of each row of ``other`` (..., L) from ``base`` (L). Undefined on both sides counts as equal, on one as infinite."""
    none = np.isnan(base)
    d, safe = other - base, base
    if np.isnan(d).any():
        d = np.where(none & np.isnan(other), 0.0, d)
        d = np.where(np.isnan(d), np.inf, d)
        safe = np.where(none, 0.0, base)
    with np.errstate(invalid="ignore", divide="ignore"):
        if kind == "mae":
            return np.abs(d).mean(-1)
        if kind == "rmse":
            return np.sqrt((d * d).mean(-1))
        if kind == "chebyshev":
            return np.abs(d).max(-1)
        if kind == "mape":
            return (np.abs(d) / np.maximum(np.abs(safe), 1e-12)).mean(-1)
        if kind == "range_rmse":
            return np.sqrt((d * d).mean(-1)) / max(float(np.ptp(safe)), 1e-12)
        if kind == "msmape":
            mean = np.cumsum(safe) / np.arange(1, len(safe) + 1)
            spread = np.array([np.abs(safe[:i] - mean[i - 1]).mean() if i else 0.0 for i in range(len(safe))])
            return (np.abs(d) / np.maximum(np.abs(safe + np.where(np.isinf(d), 0, d) + safe) / 2 + spread, 1e-12)).mean(-1)
    raise ValueError(f"unknown distance {kind}")
