"""Test series on the given tables, each as ``(series_id, pos, value)``. Sums run over integer cents, hence exact."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.series import assign_pos, to_grid
from .tables import load_table

ORIGIN = "2024-01-01"


def _slots(df: DataFrame, seconds: int) -> DataFrame:
    since = F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lit(ORIGIN).cast("timestamp"))
    return df.withColumn("pos", F.floor(since / (seconds * 1_000_000)).cast("long"))


def _regular(spark, sf_dir, seconds: int, n: int, keys: list[str] | None = None) -> DataFrame:
    """``(key..., pos, cents, n)`` on the full grid; cents and n are null in empty slots."""
    keys = keys or []
    e = _slots(load_table(spark, sf_dir, "events").select("ts", "value", *keys), seconds)
    return to_grid(e.groupBy(*keys, "pos").agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"), F.count("*").alias("n")), n, keys)


def _named(df: DataFrame, name, value) -> DataFrame:
    return df.select((F.lit(name) if isinstance(name, str) else name).alias("series_id"), F.col("pos").cast("long"), value.cast("double").alias("value"))


def _wave(period: int, amplitude: float, shift: int = 0):
    return F.lit(amplitude) * F.sin(F.lit(2 * math.pi) * (F.col("pos") + shift) / F.lit(float(period)))


def day_sum(spark, sf_dir):
    return _named(_regular(spark, sf_dir, 86400, 30), "day_sum", F.coalesce("cents", F.lit(0)) / 100.0)


def hour_sum(spark, sf_dir):
    return _named(_regular(spark, sf_dir, 3600, 720), "hour_sum", F.coalesce("cents", F.lit(0)) / 100.0)


def hour_count(spark, sf_dir):
    return _named(_regular(spark, sf_dir, 3600, 720), "hour_count", F.coalesce("n", F.lit(0)))


def hour_mean(spark, sf_dir):
    from ..operators.series import fill

    return fill(_named(_regular(spark, sf_dir, 3600, 720), "hour_mean", F.col("cents") / 100.0 / F.col("n")), "linear")


def hour_season(spark, sf_dir):
    return _named(hour_mean(spark, sf_dir), "hour_season", F.col("value") + _wave(24, 60.0))


def hour_season_type(spark, sf_dir):
    """One series per event type, phases two hours apart."""
    from ..operators.series import fill

    types = F.array(*[F.lit(t) for t in ("click", "error", "purchase", "signup", "view")])
    g = _regular(spark, sf_dir, 3600, 720, ["event_type"])
    s = fill(_named(g, F.col("event_type"), F.col("cents") / 100.0 / F.col("n")), "linear")
    phase = (F.array_position(types, F.col("series_id")) - 1) * 2
    wave = F.lit(60.0) * F.sin(F.lit(2 * math.pi) * (F.col("pos") + phase) / F.lit(24.0))
    return s.select("series_id", "pos", (F.col("value") + wave).alias("value"))


def _running(df: DataFrame, name: str) -> DataFrame:
    """Running sum of the value less its mean; two aggregations over one small ordered series per key."""
    w = Window.partitionBy("series_id")
    centred = df.withColumn("value", F.col("value") - F.avg("value").over(w))
    return _named(centred.withColumn("value", F.sum("value").over(w.orderBy("pos").rowsBetween(Window.unboundedPreceding, 0))), name, F.col("value"))


def hour_runtotal(spark, sf_dir):
    return _running(hour_sum(spark, sf_dir), "hour_runtotal")


def minute_count(spark, sf_dir):
    return _named(_regular(spark, sf_dir, 60, 43200), "minute_count", F.coalesce("n", F.lit(0)))


def minute_sum(spark, sf_dir):
    return _named(_regular(spark, sf_dir, 60, 43200), "minute_sum", F.coalesce("cents", F.lit(0)) / 100.0)


def minute_season(spark, sf_dir):
    return _named(minute_sum(spark, sf_dir), "minute_season", F.col("value") + _wave(1440, 60.0))


def events_raw(spark, sf_dir):
    e = load_table(spark, sf_dir, "events").select("event_id", "value")
    return assign_pos(e.select(F.lit("events_raw").alias("series_id"), "event_id", F.col("value").cast("double")), "event_id")


def events_running(spark, sf_dir):
    return _running(events_raw(spark, sf_dir), "events_running")


def user_seq(spark, sf_dir):
    e = load_table(spark, sf_dir, "events").select(F.col("user_id").cast("string").alias("series_id"), "ts", F.col("value").cast("double"))
    return assign_pos(e, "ts")


def day_qty(spark, sf_dir):
    li = load_table(spark, sf_dir, "lineitem").select(F.col("l_shipdate").cast("date").alias("d"), "l_quantity")
    bounds = li.agg(F.min("d").alias("lo"), F.max("d").alias("hi"))
    grid = bounds.select(F.explode(F.sequence("lo", "hi")).alias("d"), "lo")
    daily = li.groupBy("d").agg(F.sum(F.round(F.col("l_quantity")).cast("long")).alias("q"))
    return _named(grid.join(daily, "d", "left").withColumn("pos", F.date_diff("d", "lo")), "day_qty", F.coalesce("q", F.lit(0)))


def day_qty_ma(spark, sf_dir):
    w = Window.partitionBy("series_id").orderBy("pos").rowsBetween(-29, 0)
    s = day_qty(spark, sf_dir).withColumn("value", F.avg("value").over(w)).where("pos >= 29")
    return _named(s.withColumn("pos", F.col("pos") - 29), "day_qty_ma", F.col("value"))


def day_qty_season(spark, sf_dir):
    s = day_qty(spark, sf_dir)
    s = s.withColumn("sd", F.stddev_pop("value").over(Window.partitionBy("series_id")))
    return _named(s, "day_qty_season", F.col("value") + 2 * F.col("sd") * F.sin(F.lit(2 * math.pi) * F.col("pos") / F.lit(365.0)))


def part_price(spark, sf_dir):
    p = load_table(spark, sf_dir, "part").select(F.lit("part_price").alias("series_id"), "p_partkey", F.col("p_retailprice").cast("double").alias("value"))
    return assign_pos(p, "p_partkey")


def supplier_month(spark, sf_dir):
    li = load_table(spark, sf_dir, "lineitem")
    cents = F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")) * 100).cast("long")
    m = li.groupBy(F.col("l_suppkey").cast("string").alias("series_id"), F.date_trunc("month", "l_shipdate").alias("month")).agg((F.sum(cents) / 100.0).alias("value"))
    return assign_pos(m, "month")


def embed_dims(spark, sf_dir):
    return load_table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("string").alias("series_id"), F.posexplode("embedding").alias("pos", "value")).select("series_id", F.col("pos").cast("long"), F.col("value").cast("double"))


def synthetic(spark: SparkSession, power: int):
    noise = (F.pmod(F.xxhash64("id"), F.lit(1_000_003)) / 1_000_003.0 - 0.5) * 0.4
    return spark.range(1 << power).select(F.lit(f"synthetic_{power}").alias("series_id"), F.col("id").alias("pos"), (F.sin(F.lit(2 * math.pi) * F.col("id") / 64.0) + noise).alias("value"))


def anomaly_set(spark, sf_dir):
    """Three altered copies of each typed hourly series: a window is flattened, reversed or scaled. Also ``(series_id, begin, end)``."""
    s = hour_season_type(spark, sf_dir)
    kinds = s.crossJoin(spark.createDataFrame([(0, "flat"), (1, "reversed"), (2, "scaled")], "k int, kind string"))
    types = F.array(*[F.lit(t) for t in ("click", "error", "purchase", "signup", "view")])
    j = (F.array_position(types, F.col("series_id")) - 1) * 3 + F.col("k")
    kinds = kinds.withColumn("begin", (300 + 17 * j).cast("long")).withColumn("at", F.when(F.col("pos").between(F.col("begin"), F.col("begin") + 39), F.col("pos") - F.col("begin")))
    w = Window.partitionBy("series_id", "kind")
    first = F.max(F.when(F.col("at") == 0, F.col("value"))).over(w)
    turned = F.element_at(F.map_from_entries(F.collect_list(F.when(F.col("at").isNotNull(), F.struct(39 - F.col("at"), "value"))).over(w)), F.col("at"))
    value = F.when(F.col("at").isNull(), F.col("value")).when(F.col("kind") == "flat", first).when(F.col("kind") == "reversed", turned).otherwise(F.col("value") * 0.3)
    named = F.concat_ws("_", "series_id", "kind")
    return kinds.select(named.alias("series_id"), "pos", value.alias("value"), "begin")
