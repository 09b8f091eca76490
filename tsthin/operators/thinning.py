"""Thinning of many series at once, one task per series, and its dual; the size dispatcher; trial-and-error exploration.

Every call takes ``(series_id, pos, value)`` with consecutive positions and returns kept points
``(series_id, pos, value, n, deviation, evaluated, redrawn)``. One exchange by series, no other.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernel import lines
from ..kernel.greedy import Rules, thin_array, thin_arrays, together

KEPT = "series_id string, pos long, value double, n long, deviation double, evaluated long, redrawn long"
METHODS = {
    "greedy": None,
    "triangle_area": lambda x, r: lines.triangle_area(x, r),
    "turning_sum": lambda x, r: lines.turning_points(x, r, "sum_abs"),
    "turning_err": lambda x, r: lines.turning_points(x, r, "mean_abs_err"),
    "perceptual_vertical": lambda x, r: lines.perceptual_points(x, r, "vertical"),
    "perceptual_euclidean": lambda x, r: lines.perceptual_points(x, r, "euclidean"),
}


def thin(df: DataFrame, rules: Rules, method: str = "greedy", pin: str | None = None) -> DataFrame:
    """Thin every series under the given rules. ``pin``: name of a boolean column of points that must stay."""
    run = METHODS[method]

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos", kind="stable")
        x = g["value"].to_numpy(float)
        if np.isnan(x).any():
            raise ValueError("missing values: fill the series first")
        if run is None:
            kept, d, counters = thin_array(x, rules, g[pin].to_numpy(bool) if pin else None)
        else:
            (kept, d), counters = run(x, rules), {}
        out = g.iloc[kept][["series_id", "pos", "value"]].copy()
        return out.assign(n=len(x), deviation=float(d), evaluated=int(counters.get("evaluated", 0)), redrawn=int(counters.get("redrawn", 0)))

    cols = ["series_id", "pos", "value"] + ([pin] if pin else [])
    dealt = spread(df.select(*cols))
    if run is None and together(rules):
        return dealt.sortWithinPartitions("series_id", "pos").mapInPandas(lambda batches: _runs(batches, rules, pin), KEPT)
    return dealt.groupBy("series_id").applyInPandas(one, KEPT)


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """Rows by series over a fixed number of partitions. Adaptive execution would merge them by bytes, and series are few bytes for much work."""
    return df.repartition(4 * df.sparkSession.sparkContext.defaultParallelism, *(keys or ("series_id",)))


def _runs(batches, rules: Rules, pin: str | None, points: int = 65_536):
    """Thin series that follow each other in sorted batches, many at once: as soon as so many points are complete."""
    held: list[pd.DataFrame] = []
    size = 0
    for b in batches:
        if not len(b):
            continue
        held.append(b)
        size += len(b)
        if size < points:
            continue
        g = pd.concat(held, ignore_index=True)
        codes = pd.factorize(g["series_id"])[0]
        last = int(np.argmax(codes == codes[-1]))  # the last series may go on in the next batch
        held, size = [g.iloc[last:]], len(g) - last
        if last:
            yield _many(g.iloc[:last], codes[:last], rules, pin)
        else:
            points *= 2
    if held:
        g = pd.concat(held, ignore_index=True)
        yield _many(g, pd.factorize(g["series_id"])[0], rules, pin)


def _many(g: pd.DataFrame, codes: np.ndarray, rules: Rules, pin: str | None) -> pd.DataFrame:
    x = g["value"].to_numpy(float)
    if np.isnan(x).any():
        raise ValueError("missing values: fill the series first")
    cuts = np.nonzero(np.diff(codes))[0] + 1
    start = np.append(0, cuts)
    found = thin_arrays(np.split(x, cuts), rules, np.split(g[pin].to_numpy(bool), cuts) if pin else None)
    each = [len(kept) for kept, _, _ in found]
    out = g.iloc[np.concatenate([s + kept for s, (kept, _, _) in zip(start, found)])][["series_id", "pos", "value"]]
    count = lambda name: np.repeat([int(c.get(name, 0)) for _, _, c in found], each)
    n, deviation = np.repeat(np.diff(np.append(start, len(x))), each), np.repeat([float(d) for _, d, _ in found], each)
    return out.assign(n=n, deviation=deviation, evaluated=count("evaluated"), redrawn=count("redrawn"))


def thin_bounded(df, eps, lags, statistic="autocorr", distance="mae", hops="10log", max_ratio=math.inf, **more) -> DataFrame:
    """Fewest points such that the statistic of the redrawn series moves by at most ``eps`` (and the ratio stays below ``max_ratio``)."""
    pin = more.pop("pin", None)
    return thin(df, Rules(lags=tuple(lags), eps=eps, statistic=statistic, distance=distance, hops=hops, ratio=max_ratio, **more), pin=pin)


def thin_on_windows(df, eps, lags, window, agg="mean", **more) -> DataFrame:
    """As ``thin_bounded``, with the statistic of tumbling-window aggregates; single points are dropped all the same."""
    return thin_bounded(df, eps, lags, window=window, agg=agg, **more)


def thin_to_ratio(df, ratio, lags, **more) -> DataFrame:
    """Least movement of the statistic at a given ratio of points to kept points."""
    return thin_bounded(df, math.inf, lags, max_ratio=ratio, **more)


def thin_multivariate(df: DataFrame, columns: list[str], rules: Rules, combine: str = "max") -> DataFrame:
    """One kept set for several columns ``(series_id, pos, *columns)``; the deviation is the greatest (or mean) over the columns."""
    from ..kernel.greedy import Series, deviation_of, hop_count

    fold = np.max if combine == "max" else np.mean
    schema = "series_id string, pos long, " + ", ".join(f"`{c}` double" for c in columns) + ", n long, deviation double"

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos", kind="stable")
        n = len(g)
        xs = [g[c].to_numpy(float) for c in columns]
        kept, removed = np.arange(n), []
        if n >= 3:
            all_ = [Series(x, rules) for x in xs]
            a = all_[0]
            impact = np.full(n, np.inf)
            impact[1:-1] = np.round(fold([s.impacts(np.arange(1, n - 1)) for s in all_], axis=0), 9)
            hops = hop_count(rules.hops, n, a.window)
            while n / max(1, a.n_live) < rules.ratio:
                i = int(np.argmin(impact))
                if not np.isfinite(impact[i]):
                    break
                sums = [s.what_if(np.array([i]))[0] for s in all_]
                ds = [float(_distance(s, t)) for s, t in zip(all_, sums)]
                if fold(ds) > rules.eps:
                    break
                for s, t, d in zip(all_, sums, ds):
                    s.commit(i, t, d)
                removed.append(i)
                impact[i] = np.inf
                near = a.neighbours(i, hops)
                if len(near):
                    impact[near] = np.round(fold([s.impacts(near) for s in all_], axis=0), 9)
            while True:
                kept = np.nonzero(a.alive)[0]
                d = float(fold([deviation_of(x, kept, rules) for x in xs]))
                if d <= rules.eps * (1 + 1e-9) + 1e-12 or not removed:
                    break
                a.alive[removed.pop()] = True
        else:
            d = 0.0
        return g.iloc[kept][["series_id", "pos", *columns]].assign(n=n, deviation=d)

    return df.select("series_id", "pos", *columns).groupBy("series_id").applyInPandas(one, schema)


def _distance(series, sums):
    from ..kernel import stats

    return stats.distance(series.rules.distance, series.base, series.vector(sums))


def thin_any(df: DataFrame, rules: Rules, max_points: int = 2_000_000, chunk: int = 200_000) -> DataFrame:
    """Size dispatcher: series beyond ``max_points`` go through chunks, the others through one task each. One cheap count decides."""
    from .chunked import thin_chunked

    sizes = df.groupBy("series_id").agg(F.count("*").alias("_n"))
    if sizes.where(F.col("_n") > max_points).isEmpty():
        return thin(df, rules).select("series_id", "pos", "value")
    small = df.join(sizes.where(F.col("_n") <= max_points), "series_id", "left_semi")
    large = df.join(sizes.where(F.col("_n") > max_points), "series_id", "left_semi")
    out = thin(small, rules).select("series_id", "pos", "value")
    return out.unionByName(thin_chunked(large, rules, chunk=chunk).select("series_id", "pos", "value"))


def meta(kept: DataFrame) -> DataFrame:
    """One row per series: ``n, n_kept, ratio, deviation``."""
    return kept.groupBy("series_id").agg(F.max("n").alias("n"), F.count("*").alias("n_kept"), (F.max("n") / F.count("*")).alias("ratio"), F.max("deviation").alias("deviation"))
