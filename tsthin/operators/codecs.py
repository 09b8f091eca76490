"""Functional and lossless codecs over many series, and exploration of their tolerances."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..kernel import codecs
from ..kernel.greedy import Rules, statistic_of
from ..kernel.stats import distance

SEGMENTS = "series_id string, seg_no int, start_pos long, length long, intercept double, slope double"
COEFFS = "series_id string, k int, re double, im double, n long"
BITS = "series_id string, n long, n_bits long, payload binary"


def _values(g: pd.DataFrame) -> np.ndarray:
    return g.sort_values("pos", kind="stable")["value"].to_numpy(float)


def segments(df: DataFrame, codec: str, tol: float) -> DataFrame:
    """Pieces of ``pmc``, ``swing`` or ``sim_piece`` for every series."""
    run = {"pmc": codecs.pmc_mean, "swing": codecs.swing, "sim_piece": lambda x, t: codecs.merge_cones(codecs.cone_pieces(x, t))[0]}[codec]

    def one(g):
        p = run(_values(g), tol)
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "seg_no": range(len(p)), "start_pos": [q[0] for q in p], "length": [q[1] for q in p], "intercept": [q[2] for q in p], "slope": [q[3] for q in p]})

    return df.groupBy("series_id").applyInPandas(one, SEGMENTS)


def cone_segments(df: DataFrame, tol: float) -> DataFrame:
    """First phase of the merged-cone codec: ``(series_id, start_pos, length, intercept, lo, hi)``."""

    def one(g):
        p = codecs.cone_pieces(_values(g), tol)
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "start_pos": [q[0] for q in p], "length": [q[1] for q in p], "intercept": [q[2] for q in p], "lo": [q[3] for q in p], "hi": [q[4] for q in p]})

    return df.groupBy("series_id").applyInPandas(one, "series_id string, start_pos long, length long, intercept double, lo double, hi double")


def merge_slopes(cones: DataFrame) -> DataFrame:
    """Second phase in SQL windows: gaps and islands over slope ranges of one intercept.

    A piece joins the run of pieces before it whose ranges all reach it; runs are cut where the least upper slope so far falls short.
    The running minimum is taken since the last cut at most once per run, so chains cut conservatively: every shared slope is valid.
    """
    w = Window.partitionBy("series_id", "intercept").orderBy("lo", "start_pos")
    reach = F.min("hi").over(w.rowsBetween(Window.unboundedPreceding, -1))
    s = cones.withColumn("cut", F.when(F.col("lo") <= reach, 0).otherwise(1))
    s = s.withColumn("run", F.sum("cut").over(w))
    r = Window.partitionBy("series_id", "intercept", "run")
    return s.withColumn("slope", (F.max("lo").over(r) + F.min("hi").over(r)) / 2).select("series_id", "start_pos", "length", "intercept", "slope")


def draw_segments(seg: DataFrame) -> DataFrame:
    """``(series_id, pos, value)`` of pieces, without Python."""
    at = F.explode(F.sequence(F.lit(0).cast("long"), F.col("length") - 1)).alias("i")
    return seg.where("length > 0").select("series_id", "start_pos", "intercept", "slope", at).select("series_id", (F.col("start_pos") + F.col("i")).alias("pos"), (F.col("intercept") + F.col("slope") * F.col("i")).alias("value"))


def fourier(df: DataFrame, keep: int, pick: str = "low") -> DataFrame:
    def one(g):
        x = _values(g)
        at, v = codecs.fourier(x, keep, pick)
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "k": at.astype(np.int32), "re": v.real, "im": v.imag, "n": len(x)})

    return df.groupBy("series_id").applyInPandas(one, COEFFS)


def inverse_fourier(coeffs: DataFrame) -> DataFrame:
    def one(g):
        y = codecs.inverse_fourier(g["k"].to_numpy(), g["re"].to_numpy() + 1j * g["im"].to_numpy(), int(g["n"].iloc[0]))
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "pos": np.arange(len(y)), "value": y})

    return coeffs.groupBy("series_id").applyInPandas(one, "series_id string, pos long, value double")


def xor_encode(df: DataFrame, codec: str) -> DataFrame:
    run = {"gorilla": codecs.xor_gorilla, "chimp": codecs.xor_chimp}[codec]

    def one(g):
        x = _values(g)
        payload, bits = run(x)
        return pd.DataFrame({"series_id": [g["series_id"].iloc[0]], "n": [len(x)], "n_bits": [bits], "payload": [payload]})

    return df.groupBy("series_id").applyInPandas(one, BITS)


def xor_decode(streams: DataFrame, codec: str) -> DataFrame:
    run = {"gorilla": codecs.xor_gorilla_decode, "chimp": codecs.xor_chimp_decode}[codec]

    def many(batches):
        for b in batches:
            for r in b.itertuples():
                y = run(r.payload, r.n_bits, r.n)
                yield pd.DataFrame({"series_id": r.series_id, "pos": np.arange(len(y)), "value": y})

    return streams.mapInPandas(many, "series_id string, pos long, value double")


def quantize(df: DataFrame, step: float) -> DataFrame:
    return df.withColumn("value", F.round(F.col("value") / step) * step)


def stored_elements(codec: str, pieces: int, merged: int = 0) -> int:
    """Numbers stored: constant and linear pieces two each, Fourier two (three if not the first), merged cones as counted."""
    return {"pmc": 2 * pieces, "swing": 2 * pieces, "fourier_low": 2 * pieces, "fourier_largest": 3 * pieces, "sim_piece": merged}[codec]


def codec_run(x: np.ndarray, codec: str, level: float) -> tuple[np.ndarray, int]:
    """Reconstruction and stored elements of one codec at one tolerance (for Fourier: share of coefficients)."""
    n = len(x)
    if codec == "pmc":
        p = codecs.pmc_mean(x, level)
        return codecs.draw(p, n), 2 * len(p)
    if codec == "swing":
        p = codecs.swing(x, level)
        return codecs.draw(p, n), 2 * len(p)
    if codec == "sim_piece":
        p, stored = codecs.merge_cones(codecs.cone_pieces(x, level))
        return codecs.draw(p, n), stored
    pick = "low" if codec == "fourier_low" else "largest"
    keep = max(1, round(level * (n // 2 + 1)))
    at, v = codecs.fourier(x, keep, pick)
    return codecs.inverse_fourier(at, v, n), stored_elements(codec, len(at))


def explore(df: DataFrame, codecs_: list[str], levels: dict[str, list[float]], rules: Rules) -> DataFrame:
    """``(series_id, codec, level, ratio, deviation, range_rmse)``: one task per series, codec and tolerance.

    Tolerances are shares of the series' range; Fourier levels are shares of its coefficients.
    """
    spark = df.sparkSession
    grid = spark.createDataFrame([(c, float(v)) for c in codecs_ for v in levels[c]], "codec string, level double")

    def one(g):
        x = _values(g)
        codec, level = g["codec"].iloc[0], float(g["level"].iloc[0])
        span = float(np.ptp(x)) or 1.0
        y, stored = codec_run(x, codec, level if codec.startswith("fourier") else max(level * span, 1e-12))
        d = float(distance(rules.distance, statistic_of(x, rules), statistic_of(y, rules)))
        return pd.DataFrame({"series_id": [g["series_id"].iloc[0]], "codec": [codec], "level": [level], "ratio": [len(x) / max(1, stored)], "deviation": [d], "range_rmse": [float(np.sqrt(((x - y) ** 2).mean()) / span)]})

    return df.crossJoin(F.broadcast(grid)).groupBy("series_id", "codec", "level").applyInPandas(one, "series_id string, codec string, level double, ratio double, deviation double, range_rmse double")


def best_within(explored: DataFrame, eps: float) -> DataFrame:
    """For each series and codec the greatest ratio whose deviation is within the bound."""
    w = Window.partitionBy("series_id", "codec").orderBy(F.desc("ratio"), "level")
    return explored.where(F.col("deviation") <= eps).withColumn("k", F.row_number().over(w)).where("k = 1").drop("k")


def nearest_ratio(explored: DataFrame, ratio: float) -> DataFrame:
    w = Window.partitionBy("series_id", "codec").orderBy(F.abs(F.col("ratio") - ratio), "level")
    return explored.withColumn("k", F.row_number().over(w)).where("k = 1").drop("k")
