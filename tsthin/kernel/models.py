"""Forecasting models in NumPy: exponential smoothing, seasonal decomposition, ARIMA, harmonic regression, a small LSTM."""

from __future__ import annotations

import numpy as np


def holt_winters(x, period: int, horizon: int, seasonal: str = "add", damped: bool = False) -> np.ndarray:
    """Level, trend and season with weights chosen on a grid and refined by coordinates on one-step squared error."""
    x = np.asarray(x, float)
    if len(x) < 2 * period:
        return np.full(horizon, x[-1] if len(x) else np.nan)
    shift = 0.0
    if seasonal == "mul":
        shift = max(0.0, 1e-3 - x.min())
        x = x + shift
    l0, l1 = x[:period].mean(), x[period : 2 * period].mean()
    s0 = x[:period] - l0 if seasonal == "add" else x[:period] / l0
    phi = 0.98 if damped else 1.0

    def run(w, forecast=False):
        a, b, g = w  # arrays of candidate weights
        level, trend = np.full(len(a), l0), np.full(len(a), (l1 - l0) / period)
        season, err = np.tile(s0, (len(a), 1)), np.zeros(len(a))
        for t, v in enumerate(x):
            s = season[:, t % period]
            base = level + phi * trend
            f = base + s if seasonal == "add" else base * s
            e = v - f
            err += np.minimum(e * e, 1e12)
            new = a * (v - s if seasonal == "add" else v / np.where(np.abs(s) < 1e-9, 1e-9, s)) + (1 - a) * base
            trend = b * (new - level) + (1 - b) * phi * trend
            season[:, t % period] = g * (v - new if seasonal == "add" else v / np.where(np.abs(new) < 1e-9, 1e-9, new)) + (1 - g) * s
            level = new
        if not forecast:
            return err
        h = np.arange(1, horizon + 1)
        damp = np.cumsum(phi**h)
        s = season[0, (len(x) + h - 1) % period]
        return (level[0] + damp * trend[0] + s if seasonal == "add" else (level[0] + damp * trend[0]) * s) - shift

    grid = np.array(np.meshgrid([0.05, 0.2, 0.5, 0.8], [0.0, 0.02, 0.1], [0.05, 0.2, 0.5], indexing="ij")).reshape(3, -1)
    best = grid[:, int(np.argmin(run(grid)))]
    for step in (0.1, 0.03, 0.01):
        moves = np.clip(best[:, None] + step * np.array([[0, 1, -1, 0, 0, 0, 0], [0, 0, 0, 1, -1, 0, 0], [0, 0, 0, 0, 0, 1, -1]]), 0, 0.999)
        best = moves[:, int(np.argmin(run(moves)))]
    return run(best[:, None], True)


def _loess(y: np.ndarray, span: int) -> np.ndarray:
    """Local linear regression with tricube weights at every position."""
    n = len(y)
    q = min(max(3, span), n)
    if n <= 2:
        return y.copy()
    pos = np.arange(n)
    lo = np.clip(pos - q // 2, 0, n - q)
    idx = lo[:, None] + np.arange(q)
    u = idx - pos[:, None]
    w = (1 - (np.abs(u) / (np.abs(u).max(1, keepdims=True) + 1)) ** 3) ** 3
    v = y[idx]
    sw, sx, sxx = w.sum(1), (w * u).sum(1), (w * u * u).sum(1)
    sy, sxy = (w * v).sum(1), (w * u * v).sum(1)
    den = sw * sxx - sx * sx
    return np.where(np.abs(den) > 1e-12, (sxx * sy - sx * sxy) / np.where(den == 0, 1, den), sy / sw)


def stl(x, period: int, loops: int = 2) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Trend, season and remainder by alternating smoothing of cycle-subseries and trend."""
    x = np.asarray(x, float)
    n = len(x)
    trend, season = np.zeros(n), np.zeros(n)
    for _ in range(loops):
        d = x - trend
        for k in range(min(period, n)):
            season[k::period] = _loess(d[k::period], 7 if n >= 14 * period else max(3, (n // period) | 1))
        around = np.concatenate([season[:period], season, season[-period:]])  # the season goes on at both ends
        low = np.convolve(around, np.ones(period) / period, "same")[min(period, n) : min(period, n) + n]
        season = season - _loess(low, period | 1)
        trend = _loess(x - season, int(1.5 * period) | 1)
    return trend, season, x - trend - season


def seasonal_strength(x, period: int) -> float:
    _, s, r = stl(x, period)
    v = np.var(s + r)
    return float(max(0.0, 1 - np.var(r) / v)) if v > 0 else 0.0


def exponential(x, horizon: int, trend: bool = True) -> np.ndarray:
    """Damped-trend exponential smoothing of a series without season."""
    x = np.asarray(x, float)
    a, b = (g.ravel() for g in np.meshgrid(np.linspace(0.05, 0.95, 10), [0.0, 0.05, 0.2] if trend else [0.0], indexing="ij"))
    level, slope, err = np.full(len(a), x[0]), np.zeros(len(a)), np.zeros(len(a))
    for v in x[1:]:
        base = level + 0.95 * slope
        err += (v - base) ** 2
        new = a * v + (1 - a) * base
        slope, level = b * (new - level) + (1 - b) * 0.95 * slope, new
    k = int(np.argmin(err))
    return level[k] + slope[k] * np.cumsum(0.95 ** np.arange(1, horizon + 1))


def arima(x, horizon: int, max_p: int = 3, max_q: int = 2) -> np.ndarray:
    """ARIMA with d in {0, 1} by variance, AR and MA terms by regression on lagged values and innovations, order by corrected AIC."""
    x = np.asarray(x, float)
    d = int(len(x) > 3 and np.std(np.diff(x)) < 0.7 * np.std(x))
    y = np.diff(x) if d else x
    mean = y.mean()
    z = y - mean
    n = len(z)
    long = min(12, max(1, n // 6))
    rows = np.array([z[t - long : t][::-1] for t in range(long, n)]) if n > long else np.zeros((0, long))
    e = np.zeros(n)
    if len(rows) > long:
        e[long:] = z[long:] - rows @ np.linalg.lstsq(rows, z[long:], rcond=None)[0]
    best = (np.inf, 0, 0, np.zeros(0))
    start = long + max(max_p, max_q)
    for p in range(max_p + 1):
        for q in range(max_q + 1):
            if n - start <= p + q + 2:
                continue
            cols = [z[start - i : n - i] for i in range(1, p + 1)] + [e[start - i : n - i] for i in range(1, q + 1)]
            a = np.stack(cols, 1) if cols else np.zeros((n - start, 0))
            c = np.linalg.lstsq(a, z[start:], rcond=None)[0] if cols else np.zeros(0)
            s2 = float(np.mean((z[start:] - a @ c) ** 2)) + 1e-12
            m, k = n - start, p + q + 1
            aic = m * np.log(s2) + 2 * k + 2 * k * (k + 1) / max(1, m - k - 1)
            if aic < best[0]:
                best = (aic, p, q, c)
    _, p, q, c = best
    zz, ee = list(z), list(e)
    scale = 10 * (np.abs(z).max() + 1e-9) if n else 1.0
    for _ in range(horizon):
        v = sum(c[i] * zz[-1 - i] for i in range(p)) + sum(c[p + i] * ee[-1 - i] for i in range(q))
        zz.append(float(np.clip(v, -scale, scale)))
        ee.append(0.0)
    out = np.array(zz[n:]) + mean
    return x[-1] + np.cumsum(out) if d else out


def stl_ets(x, period: int, horizon: int) -> np.ndarray:
    _, s, _ = stl(x, period)
    return exponential(np.asarray(x) - s, horizon) + s[len(s) - period + np.arange(horizon) % period]


def stl_arima(x, period: int, horizon: int) -> np.ndarray:
    _, s, _ = stl(x, period)
    return arima(np.asarray(x) - s, horizon) + s[len(s) - period + np.arange(horizon) % period]


def harmonic(x, period: int, horizon: int, k: int = 3) -> np.ndarray:
    """Regression on sine and cosine pairs and a trend, ARIMA on what is left."""
    x = np.asarray(x, float)
    t = np.arange(len(x) + horizon)
    cols = [np.ones(len(t)), t / max(1, len(x))]
    for j in range(1, min(k, period // 2) + 1):
        cols += [np.sin(2 * np.pi * j * t / period), np.cos(2 * np.pi * j * t / period)]
    a = np.stack(cols, 1)
    c = np.linalg.lstsq(a[: len(x)], x, rcond=None)[0]
    return a[len(x) :] @ c + arima(x - a[: len(x)] @ c, horizon)


def seasonal_naive(x, period: int, horizon: int) -> np.ndarray:
    x = np.asarray(x, float)
    return x[len(x) - period + np.arange(horizon) % period] if len(x) >= period else np.full(horizon, x[-1])


def mean_forecast(x, period: int, horizon: int) -> np.ndarray:
    return np.full(horizon, float(np.mean(x)))


def drift(x, period: int, horizon: int) -> np.ndarray:
    x = np.asarray(x, float)
    return x[-1] + (x[-1] - x[0]) / max(1, len(x) - 1) * np.arange(1, horizon + 1)


def lstm(x, period: int, horizon: int, hidden: int = 16, epochs: int = 30, seed: int = 7) -> np.ndarray:
    """One recurrent layer with gates on windows of two seasons, trained by Adam; forecasts are fed back."""
    x = np.asarray(x, float)
    mu, sd = x.mean(), x.std() or 1.0
    z, w = (x - mu) / sd, min(2 * period, max(2, len(x) // 3))
    rng = np.random.default_rng(seed)
    data = np.lib.stride_tricks.sliding_window_view(z, w + 1)
    data = data[rng.permutation(len(data))[:512]]
    if not len(data):
        return np.full(horizon, x[-1])
    p = {"u": rng.normal(0, 0.3, (1, 4 * hidden)), "v": rng.normal(0, 1 / np.sqrt(hidden), (hidden, 4 * hidden)), "b": np.zeros(4 * hidden), "o": rng.normal(0, 0.3, hidden), "c": np.zeros(1)}
    m, s = {k: np.zeros_like(v) for k, v in p.items()}, {k: np.zeros_like(v) for k, v in p.items()}
    sig = lambda a: 1 / (1 + np.exp(-np.clip(a, -30, 30)))

    def forward(seq):
        h, c, trace = np.zeros((len(seq), hidden)), np.zeros((len(seq), hidden)), []
        for t in range(seq.shape[1]):
            g = seq[:, t : t + 1] @ p["u"] + h @ p["v"] + p["b"]
            i, f, o, n = sig(g[:, :hidden]), sig(g[:, hidden : 2 * hidden] + 1), sig(g[:, 2 * hidden : 3 * hidden]), np.tanh(g[:, 3 * hidden :])
            new = f * c + i * n
            trace.append((seq[:, t : t + 1], h, c, i, f, o, n, new))
            h, c = o * np.tanh(new), new
        return h, trace

    step, best, stale = 0, np.inf, 0
    for _ in range(epochs):
        total = 0.0
        for part in np.array_split(data, max(1, len(data) // 64)):
            h, trace = forward(part[:, :w])
            e = h @ p["o"] + p["c"] - part[:, w]
            total += float(e @ e)
            grad = {k: np.zeros_like(v) for k, v in p.items()}
            grad["o"], grad["c"] = h.T @ e / len(e), np.array([e.mean()])
            dh, dc = np.outer(e, p["o"]) / len(e), np.zeros_like(h)
            for seq, hp, cp, i, f, o, n, c in reversed(trace):
                tc = np.tanh(c)
                dc = dc + dh * o * (1 - tc * tc)
                dg = np.hstack([dc * n * i * (1 - i), dc * cp * f * (1 - f), dh * tc * o * (1 - o), dc * i * (1 - n * n)])
                grad["u"] += seq.T @ dg
                grad["v"] += hp.T @ dg
                grad["b"] += dg.sum(0)
                dh, dc = dg @ p["v"].T, dc * f
            step += 1
            for k in p:
                g = np.clip(grad[k], -1, 1)
                m[k], s[k] = 0.9 * m[k] + 0.1 * g, 0.999 * s[k] + 0.001 * g * g
                p[k] = p[k] - 0.01 * (m[k] / (1 - 0.9**step)) / (np.sqrt(s[k] / (1 - 0.999**step)) + 1e-8)
        stale = 0 if total < 0.999 * best else stale + 1
        best = min(best, total)
        if stale >= 4:
            break
    seq = list(z[-w:])
    for _ in range(horizon):
        h, _ = forward(np.array([seq[-w:]]))
        seq.append(float((h @ p["o"] + p["c"])[0]))
    return np.array(seq[w:]) * sd + mu


def box_cox(x, lam: float | None = None) -> tuple[np.ndarray, float, float]:
    """Transformed values, lambda (profile likelihood on a grid from -1 to 2) and the shift that made them positive."""
    x = np.asarray(x, float)
    shift = max(0.0, 1e-3 * (np.ptp(x) or 1.0) - x.min()) if len(x) and x.min() <= 0 else 0.0
    v = x + shift
    f = lambda k: np.log(v) if abs(k) < 1e-9 else (v**k - 1) / k
    if lam is None:
        grid = np.round(np.arange(-1, 2.01, 0.1), 10)
        score = [(k - 1) * np.log(v).sum() - len(v) / 2 * np.log(np.var(f(k)) + 1e-300) for k in grid]
        lam = float(grid[int(np.argmax(score))])
    return f(lam), lam, shift


def inverse_box_cox(y, lam: float, shift: float) -> np.ndarray:
    y = np.asarray(y, float)
    return (np.exp(np.minimum(y, 700)) if abs(lam) < 1e-9 else np.maximum(lam * y + 1, 1e-9) ** (1 / lam)) - shift


MODELS = {
    "holt_winters": holt_winters, "stl_ets": stl_ets, "stl_arima": stl_arima, "dhr_arima": harmonic, "lstm": lstm,
    "seasonal_naive": seasonal_naive, "mean": mean_forecast, "drift": drift,
}
