"""Queries of the function surface: scalar, grouped, iterator and table functions, grouped maps, the data source."""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Decimal

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from ..operators import series
from ..plans.series_queries import DAY, HOUR, TYPES, USERS, lag_corr, rounded
from ..sources import fixtures as fx
from .register import acf_at, autocorr_udf, register_functions

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _arrays(s):
    return s.groupBy("series_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "value"))), lambda x: x["value"]).alias("xs"))


@query(lag_corr(USERS, "range(1, 4)"))
def udf_scalar_pandas(spark, d):
    a = _arrays(fx.user_seq(spark, d)).select("series_id", F.posexplode(autocorr_udf("xs", F.lit(3))).alias("i", "r"))
    return a.select("series_id", (F.col("i") + 1).cast("long").alias("lag"), F.round("r", 6).alias("r"))


@query(lag_corr(TYPES, "[2]"))
def udf_grouped_agg(spark, d):
    s = fx.hour_season_type(spark, d)
    return s.groupBy("series_id").agg(F.round(acf_at("value", "pos", F.lit(2)), 6).alias("r")).withColumn("lag", F.lit(2).cast("long"))


@query(f"SELECT series_id, pos, round((value - 50) / 10.0, 6) AS value FROM {HOUR}")
def udf_iterator(spark, d):
    @pandas_udf("double")
    def scale(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for b in batches:
            yield (b - 50) / 10.0

    return rounded(fx.hour_sum(spark, d).withColumn("value", scale("value")), "value")


@query(f"SELECT DISTINCT series_id, true AS smaller, true AS ends FROM {USERS}")
def udtf_thin(spark, d):
    register_functions(spark)
    s = fx.user_seq(spark, d)
    s.createOrReplaceTempView("fn_series")
    k = spark.sql("SELECT t.series_id, t.pos, t.value FROM thin_series(TABLE(SELECT series_id, pos, value FROM fn_series) PARTITION BY series_id ORDER BY (pos), 0.05D) t")
    a, b = s.groupBy("series_id").agg(F.count("*").alias("n"), F.max("pos").alias("hi")), k.groupBy("series_id").agg(F.count("*").alias("m"), F.min("pos").alias("klo"), F.max("pos").alias("khi"))
    return a.join(b, "series_id").select("series_id", (F.col("m") <= F.col("n")).alias("smaller"), ((F.col("klo") == 0) & (F.col("khi") == F.col("hi"))).alias("ends"))


@query(f"""WITH s AS (SELECT * FROM {DAY}), k AS (SELECT *, lead(pos) OVER (ORDER BY pos) AS nxt, lead(value) OVER (ORDER BY pos) AS nv FROM s WHERE pos % 4 = 0 OR pos = 29)
SELECT k.series_id, s.pos, round(k.value + coalesce((nv - k.value) * (s.pos - k.pos) / (nxt - k.pos)::DOUBLE, 0), 6) AS value FROM k JOIN s ON s.pos >= k.pos AND s.pos < coalesce(nxt, k.pos + 1)""")
def udtf_reconstruct(spark, d):
    register_functions(spark)
    fx.day_sum(spark, d).where("pos % 4 = 0 or pos = 29").createOrReplaceTempView("fn_kept")
    return rounded(spark.sql("SELECT t.series_id, t.pos, t.value FROM redraw_series(TABLE(SELECT series_id, pos, value FROM fn_kept) PARTITION BY series_id ORDER BY pos) t"), "value")


@query(f"SELECT DISTINCT series_id, true AS subset FROM {USERS}")
def udf_sql_thin(spark, d):
    register_functions(spark)
    _arrays(fx.user_seq(spark, d)).createOrReplaceTempView("fn_arrays")
    return spark.sql("SELECT series_id, k[0] = 0 AND element_at(k, -1) = size(xs) - 1 AND size(k) <= size(xs) AS subset FROM (SELECT series_id, xs, thin(xs, 0.05D, 5) AS k FROM fn_arrays)")


@query(f"SELECT series_id, count(*) FILTER (WHERE value > m + 1) AS above FROM (SELECT *, avg(value) OVER (PARTITION BY series_id) AS m FROM {USERS}) GROUP BY 1")
def grouped_map_cogroup(spark, d):
    """Raw series cogrouped with their (constant) models: points well above the model per series.

    Sums in double precision depend on the order of rows, so values that tie with the limit are told in decimals.
    """
    s = fx.user_seq(spark, d)
    m = s.groupBy("series_id").agg(F.avg("value").alias("m"))

    def one(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        v, limit = a["value"].dropna().to_numpy(float), float(b["m"].iloc[0]) + 1
        above, tied = v > limit, np.abs(v - limit) <= 1e-9 * max(1.0, abs(limit))
        if tied.any():
            total = sum(Decimal(repr(x)) for x in v.tolist())
            above[tied] = [(Decimal(repr(x)) - 1) * len(v) > total for x in v[tied].tolist()]
        return pd.DataFrame({"series_id": [a["series_id"].iloc[0]], "above": [int(above.sum())]})

    return s.groupBy("series_id").cogroup(m.groupBy("series_id")).applyInPandas(one, "series_id string, above long")


@query(f"""WITH s AS (SELECT * FROM {HOUR}), k AS (SELECT *, lead(pos) OVER (ORDER BY pos) AS nxt, lead(value) OVER (ORDER BY pos) AS nv FROM s WHERE pos % 4 = 0 OR pos = 719)
SELECT k.series_id, s.pos, round(k.value + coalesce((nv - k.value) * (s.pos - k.pos) / (nxt - k.pos)::DOUBLE, 0), 6) AS value FROM k JOIN s ON s.pos >= k.pos AND s.pos < coalesce(nxt, k.pos + 1)""")
def read_thinned_source(spark, d):
    """Kept points packed one row a series, read back as all positions by the Python data source."""
    from ..sources.datasource import ThinnedSource, pack

    spark.dataSource.register(ThinnedSource)
    packed = pack(fx.hour_sum(spark, d).where("pos % 4 = 0 or pos = 719"))
    return rounded(spark.read.format("thinned").option("packed", packed).load(), "value")


@query(f"SELECT series_id, count(*) AS n FROM {USERS} GROUP BY 1")
def written_series(spark, d):
    from ..plans.relational import _scratch
    from ..sources.tables import read_series, write_series

    path = _scratch(spark)
    write_series(fx.user_seq(spark, d), path, 4)
    return read_series(spark, path).groupBy("series_id").agg(F.count("*").alias("n"))


@query(f"SELECT series_id, count(*) AS n FROM {USERS} GROUP BY 1")
def fill_dropped(spark, d):
    return series.fill(fx.user_seq(spark, d), "drop").groupBy("series_id").agg(F.count("*").alias("n"))
