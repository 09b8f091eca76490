"""The experiment workloads, re-expressed on the given tables. Results are rows; orderings are reported, not forced."""

from __future__ import annotations

import time
from dataclasses import replace
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernel.greedy import Rules, thin_array, thin_at_bounds
from ..operators import anomaly, chunked, codecs, forecast, measures, reconstruct, statistics, thinning
from ..sources import fixtures as fx

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
L24, L7 = tuple(range(1, 25)), tuple(range(1, 8))
LINES = ("triangle_area", "turning_sum", "turning_err", "perceptual_vertical", "perceptual_euclidean")
LEVELS = {"pmc": [0.005, 0.01, 0.02, 0.05, 0.1, 0.2], "swing": [0.005, 0.01, 0.02, 0.05, 0.1, 0.2], "sim_piece": [0.005, 0.01, 0.02, 0.05, 0.1, 0.2], "fourier_low": [0.02, 0.05, 0.1, 0.2, 0.4], "fourier_largest": [0.01, 0.02, 0.05, 0.1, 0.2]}
BOUNDS = (1e-3, 1e-2, 5e-2)


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), parts)


def direct(spark, d) -> DataFrame:
    return union([fx.hour_season(spark, d), fx.hour_runtotal(spark, d), fx.day_qty_ma(spark, d), fx.part_price(spark, d)])


def sweep(s: DataFrame, methods, bounds, rules: dict | None = None) -> DataFrame:
    """``(series_id, method, eps, n, n_kept, ratio, deviation, range_rmse)``: one task per series and method.

    The method itself runs once, to the loosest bound; the others are read off its path.
    """
    spark = s.sparkSession
    grid = spark.createDataFrame([(m,) for m in methods], "method string")
    bounds, more = [float(e) for e in bounds], rules or {}

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos", kind="stable")
        x, m = g["value"].to_numpy(float), g["method"].iloc[0]
        r = Rules(**({"lags": L24, "hops": "5log"} | more))
        found = thin_at_bounds(x, r, bounds) if m == "greedy" else [thinning.METHODS[m](x, replace(r, eps=e)) for e in bounds]
        drawn = [np.interp(np.arange(len(x)), kept, x[kept]) for kept, _ in found]
        return pd.DataFrame(
            {
                "series_id": g["series_id"].iloc[0], "method": m, "eps": bounds, "n": len(x), "n_kept": [len(k) for k, _ in found],
                "ratio": [len(x) / max(1, len(k)) for k, _ in found], "deviation": [d for _, d in found],
                "range_rmse": [float(np.sqrt(((x - y) ** 2).mean()) / (np.ptp(x) or 1.0)) for y in drawn],
            }
        )

    schema = "series_id string, method string, eps double, n long, n_kept long, ratio double, deviation double, range_rmse double"
    return thinning.spread(s.crossJoin(F.broadcast(grid)), "series_id", "method").groupBy("series_id", "method").applyInPandas(one, schema)


@query()
def w1_feature_study(spark, d):
    """Which feature's change goes with a worse forecast: Fourier truncation at several levels, decomposition with smoothing."""
    s = fx.hour_season_type(spark, d)
    train = s.where("pos < 696")
    test = s.where("pos >= 696")
    parts, base = [], forecast.accuracy(forecast.forecast(train, ["stl_ets"], 24), test).select("series_id", F.col("mae").alias("base"))
    raw = statistics.profile_series(train).select("series_id", F.col("acf1").alias("a1"), F.col("acf10").alias("a10"), F.col("pacf5").alias("p5"))
    for keep in (8, 20, 60, 150):
        y = codecs.inverse_fourier(codecs.fourier(train, keep, "largest"))
        acc = forecast.accuracy(forecast.forecast(y, ["stl_ets"], 24), test).select("series_id", "mae")
        p = statistics.profile_series(y).select("series_id", "acf1", "acf10", "pacf5")
        parts.append(measures.errors(train, y).select("series_id", "range_rmse", "psnr").join(acc, "series_id").join(p, "series_id").withColumn("keep", F.lit(keep)))
    j = union(parts).join(base, "series_id").join(raw, "series_id")
    j = j.select((F.col("mae") - F.col("base")).alias("worse"), "range_rmse", "psnr", F.abs(F.col("acf1") - F.col("a1")).alias("acf1_change"), F.abs(F.col("acf10") - F.col("a10")).alias("acf10_change"), F.abs(F.col("pacf5") - F.col("p5")).alias("pacf5_change"))
    return measures.feature_correlation(j, ["range_rmse", "psnr", "acf1_change", "acf10_change", "pacf5_change"], "worse")


@query()
def w2_importance_skew(spark, d):
    """Share of the total impact held by the upper tenth of points, per series."""
    s = union([fx.hour_season(spark, d), fx.hour_runtotal(spark, d), fx.day_qty(spark, d), fx.part_price(spark, d)])
    k = statistics.impact_skew(statistics.initial_impacts(s, list(range(1, 13))))
    return k.groupBy("series_id").agg((1 - F.max(F.when(F.col("share_of_points") <= 0.9, F.col("share_of_impact")))).alias("top_tenth"), F.max("impact").alias("greatest"))


@query("SELECT 'hour_season' AS series_id, 720 AS n UNION ALL SELECT 'hour_runtotal', 720 UNION ALL SELECT 'events_running', count(*) FROM events UNION ALL SELECT 'part_price', count(*) FROM part UNION ALL SELECT 'minute_season', 43200")
def w3_summary_lengths(spark, d):
    return w3_summary(spark, d).select("series_id", "n")


@query()
def w3_summary(spark, d):
    return statistics.profile_series(union([fx.hour_season(spark, d), fx.hour_runtotal(spark, d), fx.events_running(spark, d), fx.part_price(spark, d), fx.minute_season(spark, d)]))


@query()
def w4_ratio_by_bound(spark, d):
    """Ratio and error at each bound: the method against the line baselines, statistics of the series themselves."""
    return sweep(direct(spark, d), ("greedy", *LINES), BOUNDS)


@query()
def w4_ratio_by_bound_windows(spark, d):
    """The same with statistics of window means."""
    s = union([fx.hour_season_type(spark, d), fx.hour_runtotal(spark, d)])
    return sweep(s, ("greedy", *LINES), BOUNDS, {"lags": L7, "window": 24, "hops": "log"})


@query()
def w5_functional(spark, d):
    """Best ratio of the functional codecs within each bound, by trying tolerances."""
    e = codecs.explore(direct(spark, d), list(LEVELS), LEVELS, Rules(lags=L24))
    return union([codecs.best_within(e, b).withColumn("eps", F.lit(b)) for b in BOUNDS])


@query()
def w6_bits(spark, d):
    """Bits per value: lossless streams beside thinning (64 bits a kept point; positions free and charged)."""
    s = direct(spark, d)
    n = F.col("n")
    parts = [codecs.xor_encode(s, c).select("series_id", F.lit(c).alias("codec"), F.lit(0.0).alias("eps"), (F.col("n_bits") / n).alias("bits"), (F.col("n_bits") / n).alias("bits_with_positions")) for c in ("gorilla", "chimp")]
    k = sweep(s, ("greedy", "triangle_area"), (1e-3, 1e-2))
    parts.append(k.select("series_id", F.col("method").alias("codec"), "eps", (F.col("n_kept") * 64.0 / n).alias("bits"), (F.col("n_kept") * 96.0 / n).alias("bits_with_positions")))
    return union(parts)


@query()
def w7_error_by_ratio(spark, d):
    """Reconstruction error beside the ratio for all methods, lossy codecs included."""
    s = union([fx.hour_season(spark, d), fx.hour_runtotal(spark, d)])
    a = sweep(s, ("greedy", *LINES), BOUNDS).select("series_id", "method", "ratio", "range_rmse")
    b = codecs.explore(s, list(LEVELS), LEVELS, Rules(lags=L24)).select("series_id", F.col("codec").alias("method"), "ratio", "range_rmse")
    return a.unionByName(b)


@query()
def w8_blocking(spark, d):
    """Ratio by hops: from one to no blocking."""
    s = union([fx.hour_season(spark, d), fx.hour_runtotal(spark, d)])
    return union([sweep(s, ("greedy",), (0.01,), {"hops": h}).withColumn("hops", F.lit(h)) for h in ("1", "log", "3log", "5log", "7log", "10log", "15log", "half", "all")])


def timed(df: DataFrame) -> float:
    t0 = time.time()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - t0


@query()
def w9_compression_time(spark, d):
    """Seconds by method, halted at ratio 10; kernel time inside the task."""
    return _kernel_times(fx.hour_season(spark, d), [("greedy", h) for h in ("1", "log", "5log", "10log")] + [(m, "-") for m in LINES], {"eps": 0.01, "ratio": 10.0})


def _kernel_times(s: DataFrame, runs, rules: dict) -> DataFrame:
    grid = s.sparkSession.createDataFrame([(m, h) for m, h in runs], "method string, hops string")

    def one(g: pd.DataFrame) -> pd.DataFrame:
        x, m, h = g.sort_values("pos")["value"].to_numpy(float), g["method"].iloc[0], g["hops"].iloc[0]
        r = Rules(**({"lags": L24} | rules | ({"hops": h} if m in ("greedy", "partial") else {}) | ({"statistic": "partial"} if m == "partial" else {})))
        t0 = time.perf_counter()
        kept = (thin_array(x, r) if m in ("greedy", "partial") else thinning.METHODS[m](x, r))[0]
        took, gone = time.perf_counter() - t0, len(x) - len(kept)
        return pd.DataFrame({"series_id": [g["series_id"].iloc[0]], "method": [m], "hops": [h], "seconds": [took], "n": [len(x)], "n_kept": [len(kept)], "per_removal": [took / max(1, gone)]})

    schema = "series_id string, method string, hops string, seconds double, n long, n_kept long, per_removal double"
    return s.crossJoin(F.broadcast(grid)).groupBy("series_id", "method", "hops").applyInPandas(one, schema)


@query()
def w10_partial_time(spark, d):
    """Run time of keeping the partial autocorrelation beside the autocorrelation, for as many removals (half of the points)."""
    return _kernel_times(fx.hour_season(spark, d), [("greedy", "10log"), ("partial", "10log")], {"ratio": 2.0})


@query()
def w11_decompression_time(spark, d):
    """Seconds to redraw all values: lines from kept points, pieces, coefficients."""
    s = fx.minute_season(spark, d).cache()
    kept = chunked.thin_bulk(s, Rules(lags=L24, eps=float("inf"), ratio=10.0, window=60)).cache()
    seg = {c: codecs.segments(s, c, 60.0).cache() for c in ("pmc", "swing", "sim_piece")}
    co = codecs.fourier(s, 2160).cache()
    for x in (kept, co, *seg.values()):
        x.count()
    rows = [("lines", timed(reconstruct.reconstruct(kept))), *[(c, timed(codecs.draw_segments(x))) for c, x in seg.items()], ("fourier", timed(codecs.inverse_fourier(co)))]
    return spark.createDataFrame(rows, "codec string, seconds double")


@query()
def w12_batched_what_ifs(spark, d):
    """What fine-grained parallelism is here: all neighbours' what-ifs in one call beside one call for each."""
    from ..kernel.greedy import Series

    def one(g: pd.DataFrame) -> pd.DataFrame:
        x = g.sort_values("pos")["value"].to_numpy(float)
        s = Series(x, Rules(lags=L24))
        at = np.arange(1, min(200, len(x) - 1))
        t0 = time.perf_counter()
        many = s.what_if(at)
        t1 = time.perf_counter()
        single = np.concatenate([s.what_if(at[i : i + 1]) for i in range(len(at))])
        t2 = time.perf_counter()
        return pd.DataFrame({"series_id": [g["series_id"].iloc[0]], "together": [t1 - t0], "one_by_one": [t2 - t1], "equal": [bool(np.allclose(many, single))]})

    s = union([fx.day_qty_ma(spark, d), fx.hour_season(spark, d)])
    return s.groupBy("series_id").applyInPandas(one, "series_id string, together double, one_by_one double, equal boolean")


def _chunk_sweep(s, chunks, rules) -> DataFrame:
    """Time, ratio and global deviation by number of chunks."""
    n = s.groupBy("series_id").count().agg(F.max("count")).first()[0]
    parts = []
    for c in chunks:
        t0 = time.time()
        k = chunked.thin_chunked(s, rules, chunk=max(-(-n // c), rules.window * max(rules.lags)))
        m = k.groupBy("series_id").agg(F.count("*").alias("n_kept"), F.max("n").alias("n"), F.max("deviation").alias("deviation"), F.max("rounds").alias("rounds")).collect()
        parts += [(r["series_id"], c, time.time() - t0, r["n"] / r["n_kept"], r["deviation"], r["rounds"], bool(r["deviation"] <= rules.eps)) for r in m]
    return s.sparkSession.createDataFrame(parts, "series_id string, chunks int, seconds double, ratio double, deviation double, rounds int, within boolean")


@query()
def w13_chunks(spark, d):
    return _chunk_sweep(fx.events_running(spark, d), (1, 4, 8), Rules(lags=L7, eps=1e-4, hops="log"))


@query("SELECT 'events_running' AS series_id, c AS chunks, true AS within FROM (VALUES (1), (4), (8)) v(c)")
def w13_chunks_within_bound(spark, d):
    return w13_chunks(spark, d).select("series_id", "chunks", "within")


@query()
def w14_hybrid_lags(spark, d):
    """Chunks and batched what-ifs together, 24 and 168 lags."""
    s = fx.hour_runtotal(spark, d)
    return union([_chunk_sweep(s, (1, 4), Rules(lags=tuple(range(1, l + 1)), eps=1e-3, hops="log")).withColumn("lags", F.lit(l)) for l in (24, 168)])


def _forecast_sweep(s, models, variants: dict[str, DataFrame], box_cox=False) -> DataFrame:
    test = s.where("pos >= 696")
    parts = [forecast.accuracy(forecast.forecast(v, models, 24, box_cox=box_cox), test).withColumn("variant", F.lit(n)) for n, v in variants.items()]
    return union(parts).groupBy("variant", "model").agg(F.avg("mse").alias("mse"), F.avg("mape").alias("mape"), F.avg("mae").alias("mae"))


def _thinned(train, ratio, distance="mae", method="greedy") -> DataFrame:
    k = thinning.thin(train, Rules(lags=L24, ratio=float(ratio), eps=float("inf"), distance=distance, hops="3log"), method)
    return reconstruct.reconstruct(k.select("series_id", "pos", "value"))


@query()
def w15_exp1(spark, d):
    """Distances, line baselines and ratios: transformed, standardised, Holt-Winters, the last day held out."""
    s = fx.hour_season_type(spark, d)
    train = s.where("pos < 696")
    variants = {"raw": train} | {f"{m} {r}": _thinned(train, r, m) for m in ("mae", "rmse", "mape", "chebyshev") for r in range(2, 11)}
    variants |= {f"{m} {r}": _thinned(train, r, method=m) for m in thinning.METHODS if m != "greedy" for r in range(2, 11)}
    return _forecast_sweep(s, ["holt_winters"], variants, box_cox=True)


@query()
def w16_exp2(spark, d):
    """Three models on raw, thinned and lossily coded series."""
    s = fx.hour_season_type(spark, d)
    train = s.where("pos < 696")
    coded = {c: codecs.draw_segments(codecs.segments(train, c, 25.0)) for c in ("pmc", "swing", "sim_piece")}
    variants = {"raw": train, "thinned 5": _thinned(train, 5), "thinned 10": _thinned(train, 10), "triangle 10": _thinned(train, 10, method="triangle_area"), "fourier": codecs.inverse_fourier(codecs.fourier(train, 35))} | coded
    return _forecast_sweep(s, ["stl_arima", "stl_ets", "lstm"], variants)


@query()
def w17_exp3(spark, d):
    """Highly seasonal series to high ratios, harmonic regression and the recurrent net."""
    s = fx.hour_season_type(spark, d)
    train = s.where("pos < 696")
    variants = {"raw": train} | {f"{m} {r}": _thinned(train, r, method=m) for m in ("greedy", "triangle_area") for r in (10, 20, 50)}
    return _forecast_sweep(s, ["dhr_arima", "lstm"], variants)


@query()
def w17_seasonal_strength(spark, d):
    return forecast.seasonal_strength(union([fx.hour_season(spark, d), fx.hour_season_type(spark, d)]), 24)


@query()
def w18_anomaly(spark, d):
    """Share of altered windows found by discords, by ratio and method."""
    a = fx.anomaly_set(spark, d)
    labels = a.groupBy("series_id").agg(F.max("begin").alias("begin")).withColumn("end", F.col("begin") + 39)
    s = a.select("series_id", "pos", "value")
    lengths = range(75, 126)
    variants = {"raw": s, "pmc": codecs.draw_segments(codecs.segments(s, "pmc", 25.0)), "fourier": codecs.inverse_fourier(codecs.fourier(s, 60))}
    for m, r in (("greedy", 5), ("greedy", 15), ("triangle_area", 15)):
        variants[f"{m} {r}"] = _thinned(s, r, method=m)
    found = [measures.ucr_score(anomaly.discords(v, lengths), labels, slack=75).withColumn("variant", F.lit(n)) for n, v in variants.items()]
    return union(found)


@query()
def w19_profiles(spark, d):
    """Time of the segment profile: all pairs of positions, diagonals, and on kept points without unfolding."""
    n, m = 1 << 11, 150
    s = fx.synthetic(spark, 11).cache()
    kept = chunked.thin_bulk(s, Rules(lags=tuple(range(1, 65)), eps=float("inf"), ratio=20.0)).select("series_id", "pos", "value").cache()
    kept.count()
    rows = []
    for name, df, irregular, plain in (("pairs", s, False, True), ("diagonals", s, False, False), ("kept points", kept, True, False)):
        t0 = time.time()
        top = anomaly.segment_profile(df, n, m, irregular, 8, plain).agg(F.max("distance"), F.avg("distance")).first()
        rows.append((name, time.time() - t0, float(top[0]), float(top[1])))
    return spark.createDataFrame(rows, "profile string, seconds double, greatest double, mean double")


@query()
def w20_many_series(spark, d):
    """Many sensors at once: users and suppliers."""
    s = union([fx.user_seq(spark, d), fx.supplier_month(spark, d).withColumn("series_id", F.concat(F.lit("s"), "series_id"))])
    return thinning.meta(thinning.thin_bounded(s, 0.01, (1, 2, 3, 4, 5), hops="3log"))


@query()
def forecast_models(spark, d):
    """All models on the typed hourly series, the last day held out."""
    s = fx.hour_season_type(spark, d)
    return forecast.accuracy(forecast.forecast(s.where("pos < 696"), ["holt_winters", "stl_ets", "stl_arima", "dhr_arima", "lstm", "mean", "drift"], 24), s.where("pos >= 696"))


@query("WITH s AS (SELECT event_id - (SELECT min(event_id) FROM events) AS pos, value FROM events), n AS (SELECT max(pos) AS hi FROM s) SELECT CAST(pos - (hi - 24) AS INTEGER) AS step, round(lag24, 6) AS predicted FROM (SELECT pos, lag(value, 24) OVER (ORDER BY pos) AS lag24 FROM s), n WHERE pos > hi - 24")
def forecast_seasonal_naive(spark, d):
    s = fx.events_raw(spark, d)
    hi = s.agg(F.max("pos").alias("hi"))
    train = s.join(F.broadcast(hi), F.col("pos") <= F.col("hi") - 24).select("series_id", "pos", "value")
    return forecast.forecast(train, ["seasonal_naive"], 24).select("step", F.round("predicted", 6).alias("predicted"))


@query()
def box_cox_transform(spark, d):
    return forecast.box_cox(fx.hour_season_type(spark, d))


@query()
def anomaly_discords(spark, d):
    return anomaly.discords(fx.hour_season_type(spark, d), range(75, 126))
