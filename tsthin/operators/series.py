"""Shaping series: positions, grids, filling, windows, segments, holdouts."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def assign_pos(df: DataFrame, order: str, key: str = "series_id") -> DataFrame:
    """``(key, pos, value)``: consecutive positions from 0 in the given order."""
    return df.select(key, (F.row_number().over(Window.partitionBy(key).orderBy(order)) - 1).cast("long").alias("pos"), "value")


def to_grid(df: DataFrame, n: int, keys: list[str]) -> DataFrame:
    """All positions 0..n-1 for every key; other columns are null where nothing was. The grid is generated, not shuffled."""
    spark = df.sparkSession
    grid = spark.range(n).select(F.col("id").alias("pos"))
    if keys:
        grid = df.select(*keys).distinct().crossJoin(F.broadcast(grid))
    return grid.join(df, [*keys, "pos"], "left")


def fill(df: DataFrame, how: str = "linear", key: str = "series_id") -> DataFrame:
    """Fill null values: ``zero``, ``ffill`` or ``linear`` (nearest value at the ends); ``drop`` and ``error`` as named."""
    if how == "zero":
        return df.withColumn("value", F.coalesce("value", F.lit(0.0)))
    if how == "drop":
        return df.where("value is not null")
    if how == "error":
        return df.withColumn("value", F.when(F.col("value").isNull(), F.raise_error(F.lit("missing value")).cast("double")).otherwise(F.col("value")))
    before = Window.partitionBy(key).orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    after = Window.partitionBy(key).orderBy("pos").rowsBetween(0, Window.unboundedFollowing)
    known = F.when(F.col("value").isNotNull(), F.struct("pos", "value"))
    s = df.withColumn("_a", F.last(known, True).over(before))
    if how == "ffill":
        return s.withColumn("value", F.col("_a.value")).drop("_a")
    s = s.withColumn("_b", F.first(known, True).over(after))
    share = F.try_divide(F.col("pos") - F.col("_a.pos"), F.col("_b.pos") - F.col("_a.pos"))
    line = F.col("_a.value") + (F.col("_b.value") - F.col("_a.value")) * share
    return s.withColumn("value", F.coalesce("value", line, F.col("_a.value"), F.col("_b.value"))).drop("_a", "_b")


def window_agg(df: DataFrame, k: int, agg: str = "mean", key: str = "series_id") -> DataFrame:
    """Tumbling windows of ``k`` points; a last partial window is left out."""
    f = {"mean": F.avg, "sum": F.sum, "min": F.min, "max": F.max, "count": F.count}[agg]
    w = df.groupBy(key, F.floor(F.col("pos") / k).cast("long").alias("pos")).agg(f("value").cast("double").alias("value"), F.count("*").alias("_n"))
    return w.where(F.col("_n") == k).drop("_n")


def segment(df: DataFrame, length: int, key: str = "series_id") -> DataFrame:
    """Fixed-length segments as series of their own; a last short one is left out."""
    part = F.floor(F.col("pos") / length).cast("long")
    s = df.select(F.concat_ws("#", F.col(key), part.cast("string")).alias(key), (F.col("pos") - part * length).alias("pos"), "value")
    return s.withColumn("_n", F.count("*").over(Window.partitionBy(key))).where(F.col("_n") == length).drop("_n")


def holdout(df: DataFrame, last: int, key: str = "series_id") -> tuple[DataFrame, DataFrame]:
    """``(train, test)``: all but the last points, and these."""
    n = F.max("pos").over(Window.partitionBy(key))
    s = df.withColumn("_end", n)
    return s.where(F.col("pos") <= F.col("_end") - last).drop("_end"), s.where(F.col("pos") > F.col("_end") - last).drop("_end")
