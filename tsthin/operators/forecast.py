"""Forecasts of many series and the effect of simplification on them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernel import models

FORECASTS = "series_id string, model string, step int, predicted double"


def forecast(train: DataFrame, model_names: list[str], period: int, horizon: int = 24, box_cox: bool = False) -> DataFrame:
    """``(series_id, model, step, predicted)``: one task per series and model. ``box_cox`` transforms and standardises first."""
    names = train.sparkSession.createDataFrame([(m,) for m in model_names], "model string")

    def one(g: pd.DataFrame) -> pd.DataFrame:
        x = g.sort_values("pos", kind="stable")["value"].to_numpy(float)
        name = g["model"].iloc[0]
        if box_cox:
            y, lam, shift = models.box_cox(x)
            mu, sd = y.mean(), y.std() or 1.0
            out = models.inverse_box_cox(models.MODELS[name]((y - mu) / sd, period, horizon) * sd + mu, lam, shift)
        else:
            out = models.MODELS[name](x, period, horizon)
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "model": name, "step": np.arange(1, horizon + 1, dtype=np.int32), "predicted": out})

    return train.crossJoin(F.broadcast(names)).groupBy("series_id", "model").applyInPandas(one, FORECASTS)


def accuracy(forecasts: DataFrame, test: DataFrame, by: list[str] | None = None) -> DataFrame:
    """``(series_id, *by, model, mse, mape, mae)`` against the raw horizon ``(series_id, pos, value)``."""
    first = test.groupBy("series_id").agg(F.min("pos").alias("_lo"))
    actual = test.join(first, "series_id").select("series_id", (F.col("pos") - F.col("_lo") + 1).cast("int").alias("step"), F.col("value").alias("actual"))
    e = F.col("predicted") - F.col("actual")
    return forecasts.join(actual, ["series_id", "step"]).groupBy("series_id", *(by or []), "model").agg(
        F.avg(e * e).alias("mse"), F.avg(F.try_divide(F.abs(e), F.abs("actual"))).alias("mape"), F.avg(F.abs(e)).alias("mae")
    )


def seasonal_strength(df: DataFrame, period: int) -> DataFrame:
    def one(g):
        x = g.sort_values("pos", kind="stable")["value"].to_numpy(float)
        return pd.DataFrame({"series_id": [g["series_id"].iloc[0]], "strength": [models.seasonal_strength(x, period)]})

    return df.groupBy("series_id").applyInPandas(one, "series_id string, strength double")


def box_cox(df: DataFrame) -> DataFrame:
    """``(series_id, pos, value, lambda, shift)``: transformed and standardised values with what inverts them."""

    def one(g):
        g = g.sort_values("pos", kind="stable")
        y, lam, shift = models.box_cox(g["value"].to_numpy(float))
        mu, sd = float(y.mean()), float(y.std()) or 1.0
        return pd.DataFrame({"series_id": g["series_id"], "pos": g["pos"], "value": (y - mu) / sd, "lambda": lam, "shift": shift, "mean": mu, "sd": sd})

    return df.groupBy("series_id").applyInPandas(one, "series_id string, pos long, value double, lambda double, shift double, mean double, sd double")
