"""Segment profiles and discords over many series, or in blocks over one long series."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernel import profile


def discords(df: DataFrame, lengths=range(75, 126), normalise: bool = False) -> DataFrame:
    """``(series_id, start, length, distance)``: one task per series and length, then the farthest."""
    spark = df.sparkSession
    grid = spark.createDataFrame([(int(m),) for m in lengths], "m int")

    def one(g):
        x = g.sort_values("pos", kind="stable")["value"].to_numpy(float)
        start, length, d = profile.discord(x, [int(g["m"].iloc[0])], normalise)
        return pd.DataFrame({"series_id": [g["series_id"].iloc[0]], "start": [start], "length": [length], "distance": [d]})

    found = df.crossJoin(F.broadcast(grid)).groupBy("series_id", "m").applyInPandas(one, "series_id string, start long, length int, distance double")
    best = F.max_by(F.struct("start", "length", "distance"), F.struct("distance", -F.col("length"), -F.col("start"))).alias("b")
    return found.groupBy("series_id").agg(best).select("series_id", "b.start", "b.length", "b.distance")


def segment_profile(kept_or_raw: DataFrame, n: int, m: int, irregular: bool, blocks: int = 16, plain: bool = False) -> DataFrame:
    """``(series_id, start, distance, nearest)`` of one long series, its starts cut into blocks that are tasks.

    ``irregular``: rows are kept points and are never unfolded; else all positions. The series goes to each block as
    one packed row, so its size times the number of blocks is what is shuffled.
    """
    spark = kept_or_raw.sparkSession
    packed = kept_or_raw.groupBy("series_id").agg(F.array_sort(F.collect_list(F.struct("pos", "value"))).alias("p"))
    starts = n - m + 1
    # a row of early starts meets as many others as one of late starts, so blocks are equal
    size = -(-starts // blocks)
    grid = spark.range(blocks).select(F.col("id").alias("block")).repartition(blocks, "block")

    def many(batches):
        for b in batches:
            for r in b.itertuples():
                lo, hi = r.block * size, min(starts, (r.block + 1) * size)
                if hi <= lo:
                    continue
                pos, value = np.array([q["pos"] for q in r.p]), np.array([q["value"] for q in r.p])
                if irregular:
                    d, w = profile.profile_irregular(pos, value, n, m, (lo, hi))
                else:
                    d, w = (profile.profile_pairs if plain else profile.profile_regular)(value, m, (lo, hi))
                yield pd.DataFrame({"series_id": r.series_id, "start": np.arange(lo, hi), "distance": d, "nearest": w})

    return grid.crossJoin(F.broadcast(packed)).mapInPandas(many, "series_id string, start long, distance double, nearest long")
