"""Straight-line reconstruction, point queries and aggregates on the kept form. No Python on any path."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

KEY = "series_id"


def _pieces(kept: DataFrame, key: str) -> DataFrame:
    w = Window.partitionBy(key).orderBy("pos")
    return kept.select(key, "pos", "value", F.lead("pos").over(w).alias("next"), F.lead("value").over(w).alias("next_value"))


def reconstruct(kept: DataFrame, key: str = KEY, between: tuple[int, int] | None = None) -> DataFrame:
    """``(key, pos, value)``: every position from the first to the last kept one.

    ``between`` restricts positions; pieces outside are dropped before they are unfolded.
    """
    p = _pieces(kept, key)
    last = F.coalesce(F.col("next") - 1, F.col("pos"))
    lo, hi = F.col("pos"), last
    if between:
        p = p.where((last >= between[0]) & (F.col("pos") <= between[1]))
        lo, hi = F.greatest(lo, F.lit(between[0])), F.least(hi, F.lit(between[1]))
    at = F.explode(F.sequence(lo, hi)).alias("at")
    p = p.select(key, "pos", "value", "next", "next_value", at)
    line = F.col("value") + (F.col("next_value") - F.col("value")) * F.try_divide((F.col("at") - F.col("pos")).cast("double"), (F.col("next") - F.col("pos")).cast("double"))
    return p.select(key, F.col("at").alias("pos"), F.when(F.col("at") == F.col("pos"), F.col("value")).otherwise(line).alias("value"))


def value_at(kept: DataFrame, asked: DataFrame, key: str = KEY) -> DataFrame:
    """``(key, pos, value)`` for asked ``(key, pos)``: an as-of lookup on both sides by one sort, nothing is unfolded."""
    rows = kept.select(key, "pos", F.struct("pos", "value").alias("k"), F.lit(0).alias("q")).unionByName(asked.select(key, "pos", F.lit(None).cast("struct<pos:bigint,value:double>").alias("k"), F.lit(1).alias("q")))
    w = Window.partitionBy(key).orderBy("pos", "q")
    b = Window.partitionBy(key).orderBy(F.desc("pos"), "q")
    s = rows.withColumn("a", F.last("k", True).over(w)).withColumn("b", F.last("k", True).over(b)).where("q = 1")
    share = F.try_divide((F.col("pos") - F.col("a.pos")).cast("double"), (F.col("b.pos") - F.col("a.pos")).cast("double"))
    return s.select(key, "pos", F.coalesce(F.col("a.value") + (F.col("b.value") - F.col("a.value")) * share, F.when(F.col("a.pos") == F.col("pos"), F.col("a.value"))).alias("value"))


def piecewise_agg(kept: DataFrame, key: str = KEY) -> DataFrame:
    """``(key, n, total, mean, least, greatest, second_moment)`` of the reconstruction in closed form from the pieces."""
    p = _pieces(kept, key)
    q = F.coalesce(F.col("next") - F.col("pos"), F.lit(1)).cast("double")
    slope = F.coalesce((F.col("next_value") - F.col("value")) / q, F.lit(0.0))
    v = F.col("value")
    s1 = q * v + slope * q * (q - 1) / 2
    s2 = q * v * v + v * slope * q * (q - 1) + slope * slope * q * (q - 1) * (2 * q - 1) / 6
    return p.groupBy(key).agg(
        F.sum(q).cast("long").alias("n"), F.sum(s1).alias("total"), (F.sum(s1) / F.sum(q)).alias("mean"), F.min("value").alias("least"), F.max("value").alias("greatest"), (F.sum(s2) / F.sum(q)).alias("second_moment")
    )
