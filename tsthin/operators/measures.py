"""Cost and accuracy measures as expressions and DataFrame functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

KEY = "series_id"


def compression_ratio(raw: DataFrame, kept: DataFrame, key: str = KEY) -> DataFrame:
    a = raw.groupBy(key).agg(F.count("*").alias("n"))
    b = kept.groupBy(key).agg(F.count("*").alias("n_kept"))
    return a.join(b, key, "left").select(key, "n", F.coalesce("n_kept", F.lit(0)).alias("n_kept"), F.try_divide(F.col("n").cast("double"), F.col("n_kept").cast("double")).alias("ratio"))


def bits_per_value(raw: DataFrame, kept: DataFrame, key: str = KEY, position_bits: int = 32) -> DataFrame:
    """64 bits for each kept value over the original number of values; beside it with the bits of positions."""
    r = compression_ratio(raw, kept, key)
    return r.select(key, (F.col("n_kept") * 64.0 / F.col("n")).alias("bits"), (F.col("n_kept") * (64.0 + position_bits) / F.col("n")).alias("bits_with_positions"))


def errors(raw: DataFrame, other: DataFrame, key: str = KEY, as_printed: bool = False) -> DataFrame:
    """All pointwise measures of ``other`` against ``raw``, joined on (key, pos); positions missing on one side are left out.

    ``as_printed`` also gives the form of the root mean square with 1/n outside the root.
    """
    a = raw.select(key, "pos", F.col("value").alias("x"))
    b = other.select(key, "pos", F.col("value").alias("y"))
    j = a.join(b, [key, "pos"]).withColumn("e", F.col("y") - F.col("x"))
    span = F.max("x") - F.min("x")
    rmse = F.sqrt(F.avg(F.col("e") * F.col("e")))
    out = j.groupBy(key).agg(
        F.avg(F.abs("e")).alias("mae"), F.avg(F.col("e") * F.col("e")).alias("mse"), rmse.alias("rmse"), F.try_divide(rmse, span).alias("range_rmse"),
        F.max(F.abs("e")).alias("chebyshev"), F.avg(F.try_divide(F.abs("e"), F.abs("x"))).alias("mape"),
        F.when(rmse > 0, F.log10(F.try_divide(span, rmse)) * 20).alias("psnr"), *([(F.sqrt(F.sum(F.col("e") * F.col("e"))) / F.count("*")).alias("rmse_as_printed")] if as_printed else []),
    )
    return out


def msmape(raw: DataFrame, other: DataFrame, key: str = KEY) -> DataFrame:
    """Scaled percentage error: half the absolute pair sum plus the mean absolute deviation of the prefix from its mean.

    That deviation moves with the mean; an order-statistics tree over ranks gives it in O(log n) per point.
    """
    j = raw.select(key, "pos", F.col("value").alias("x")).join(other.select(key, "pos", F.col("value").alias("y")), [key, "pos"])

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        x, y = g["x"].to_numpy(), g["y"].to_numpy()
        s = prefix_spread(x)
        half = abs(x + y) / 2 + s
        e = abs(x - y)
        return pd.DataFrame({key: [g[key].iloc[0]], "msmape": [float((e[half > 0] / half[half > 0]).sum() / len(x))]})

    return j.groupBy(key).applyInPandas(one, f"{key} string, msmape double")


def prefix_spread(x):
    """For each i the mean absolute deviation of x[:i] from its mean; 0 for the empty prefix."""
    import bisect

    import numpy as np

    n = len(x)
    order = np.sort(x)
    rank = np.searchsorted(order, x)
    count, total = np.zeros(n + 1), np.zeros(n + 1)

    def add(i, v):
        i += 1
        while i <= n:
            count[i] += 1
            total[i] += v
            i += i & -i

    def below(i):
        c = s = 0.0
        while i > 0:
            c, s = c + count[i], s + total[i]
            i -= i & -i
        return c, s

    out, run = np.zeros(n), 0.0
    used = [0] * n
    for i in range(n):
        if i:
            m = run / i
            c, s = below(bisect.bisect_right(order, m))
            out[i] = ((m * c - s) + (run - s) - m * (i - c)) / i
        add(int(rank[i]) + used[int(rank[i])], float(x[i]))
        used[int(rank[i])] += 1
        run += float(x[i])
    return out


def deviation(raw: DataFrame, other: DataFrame, lags: list[int], distance: str = "mae", key: str = KEY, statistic: str = "autocorr") -> DataFrame:
    """``(key, deviation)`` between the statistics of two series, both computed from scratch. Undefined on both sides counts as equal."""
    from .statistics import autocorr, partial_autocorr

    f = (lambda d: partial_autocorr(d, max(lags))) if statistic == "partial" else (lambda d: autocorr(d, lags))
    a, b = f(raw).withColumnRenamed("r", "a"), f(other).withColumnRenamed("r", "b")
    d = F.when(F.col("a").isNull() & F.col("b").isNull(), 0.0).when(F.col("a").isNull() | F.col("b").isNull(), float("inf")).otherwise(F.abs(F.col("a") - F.col("b")))
    kinds = {
        "mae": F.avg("d"), "rmse": F.sqrt(F.avg(F.col("d") * F.col("d"))), "chebyshev": F.max("d"),
        "mape": F.avg(F.try_divide(F.col("d"), F.abs("a"))), "range_rmse": F.try_divide(F.sqrt(F.avg(F.col("d") * F.col("d"))), F.max("a") - F.min("a")),
    }
    return a.join(b, [key, "lag"], "full").withColumn("d", d).groupBy(key).agg(kinds[distance].alias("deviation"))


def verify_bound(raw: DataFrame, kept: DataFrame, eps: float, lags: list[int], distance: str = "mae", window: int = 1, agg: str = "mean", key: str = KEY, statistic: str = "autocorr") -> DataFrame:
    """``(key, ends_kept, subset_ok, bound_ok)``, by an independent path: reconstruction and statistics in DataFrame form."""
    from .reconstruct import reconstruct
    from .series import window_agg

    ends = raw.groupBy(key).agg(F.min("pos").alias("lo"), F.max("pos").alias("hi"))
    mine = kept.groupBy(key).agg(F.min("pos").alias("k_lo"), F.max("pos").alias("k_hi"), F.count("*").alias("n_kept"))
    same = kept.select(key, "pos", F.col("value").alias("kv")).join(raw.select(key, "pos", F.col("value").alias("rv")), [key, "pos"]).where("kv = rv").groupBy(key).agg(F.count("*").alias("n_same"))
    a, b = raw.select(key, "pos", "value"), reconstruct(kept, key)
    if window > 1:
        a, b = window_agg(a, window, agg, key), window_agg(b, window, agg, key)
    d = deviation(a, b, lags, distance, key, statistic)
    j = ends.join(mine, key, "left").join(same, key, "left").join(d, key, "left")
    return j.select(
        key, F.coalesce((F.col("lo") == F.col("k_lo")) & (F.col("hi") == F.col("k_hi")), F.lit(False)).alias("ends_kept"),
        F.coalesce(F.col("n_same") == F.col("n_kept"), F.lit(False)).alias("subset_ok"), F.coalesce(F.col("deviation") <= eps * (1 + 1e-6) + 1e-9, F.lit(False)).alias("bound_ok"),
    )


def ucr_score(found: DataFrame, labels: DataFrame, slack: int = 100, key: str = KEY) -> DataFrame:
    """Share of series whose reported start lies in the labelled range, give or take the slack. ``found``: (key, start); ``labels``: (key, begin, end)."""
    hit = F.col("start").between(F.col("begin") - slack, F.col("end") + slack)
    return labels.join(found, key, "left").agg(F.avg(F.when(hit, 1.0).otherwise(0.0)).alias("score"), F.count("*").alias("series"))


def feature_correlation(results: DataFrame, features: list[str], outcome: str) -> DataFrame:
    """``(feature, r)``: Pearson correlation of each feature's change with the outcome's change over all rows."""
    pairs = F.explode(F.array(*[F.struct(F.lit(f).alias("feature"), F.col(f).cast("double").alias("v")) for f in features])).alias("p")
    return results.select(F.col(outcome).cast("double").alias("o"), pairs).groupBy("p.feature").agg(F.corr("o", "p.v").alias("r")).select("feature", "r")


def prefix_mean(df: DataFrame, key: str = KEY) -> DataFrame:
    w = Window.partitionBy(key).orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    return df.select(key, "pos", F.avg("value").over(w).alias("prefix_mean"))
