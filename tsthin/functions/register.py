"""Functions for SQL: statistics and thinning of arrays, table functions over partitions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ..kernel import stats
from ..kernel.greedy import Rules, thin_array


DOUBLES = T.ArrayType(T.DoubleType())
POINTS = T.StructType([T.StructField("series_id", T.StringType()), T.StructField("pos", T.LongType()), T.StructField("value", T.DoubleType())])


@pandas_udf(DOUBLES)
def autocorr_udf(values: pd.Series, lags: pd.Series) -> pd.Series:
    return pd.Series([stats.autocorr(np.asarray(v, float), range(1, int(l) + 1)) for v, l in zip(values, lags)])


@pandas_udf(DOUBLES)
def partial_udf(r: pd.Series) -> pd.Series:
    return pd.Series([stats.partial(np.asarray(x, float)) for x in r])


@pandas_udf(T.ArrayType(T.LongType()))
def thin_udf(values: pd.Series, eps: pd.Series, lags: pd.Series) -> pd.Series:
    return pd.Series([thin_array(v, Rules(lags=tuple(range(1, int(l) + 1)), eps=float(e)))[0] for v, e, l in zip(values, eps, lags)])


@pandas_udf(T.DoubleType())
def acf_at(value: pd.Series, pos: pd.Series, lag: pd.Series) -> float:
    """Grouped aggregate: lagged-pair autocorrelation at one lag."""
    x = value.to_numpy(float)[np.argsort(pos.to_numpy(), kind="stable")]
    return float(stats.autocorr(x, [int(lag.iloc[0])])[0]) if len(x) else float("nan")


@udtf(returnType=POINTS)
class ThinSeries:
    """``TABLE(...) PARTITION BY series_id ORDER BY pos`` to kept points, five lags, given bound."""

    def __init__(self):
        self.rows, self.eps = [], 0.01

    def eval(self, row, eps: float):
        self.eps = eps
        self.rows.append((row["series_id"], row["pos"], row["value"]))

    def terminate(self):
        x = np.array([r[2] for r in self.rows], float)
        for i in thin_array(x, Rules(lags=(1, 2, 3, 4, 5), eps=self.eps))[0]:
            yield self.rows[i]


@udtf(returnType=POINTS)
class RedrawSeries:
    """Kept points in order to every position between them; one piece is held at a time."""

    def __init__(self):
        self.last = None

    def eval(self, row):
        s, p, v = row["series_id"], row["pos"], row["value"]
        if self.last is not None:
            a, b = self.last
            for q in range(a + 1, p):
                yield s, q, b + (v - b) * (q - a) / (p - a)
        self.last = (p, v)
        yield s, p, v


def register_functions(spark: SparkSession) -> None:
    spark.udf.register("autocorr", autocorr_udf)
    spark.udf.register("partial_autocorr", partial_udf)
    spark.udf.register("thin", thin_udf)
    spark.udf.register("acf_at", acf_at)
    spark.udtf.register("thin_series", ThinSeries)
    spark.udtf.register("redraw_series", RedrawSeries)
