"""Names of all queries of the engine, with their oracle SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from .functions import queries as functions_queries
from .operators import thinning
from .plans import relational, series_queries, workloads
from .sources import fixtures
from .streaming import queries as streaming_queries

MODULES = (relational, series_queries, workloads, functions_queries, streaming_queries)


def queries() -> dict:
    return {name: f for m in MODULES for name, f in m.QUERIES.items()}


def oracles() -> dict:
    return {name: sql for m in MODULES for name, sql in m.ORACLES.items()}


def flagship(spark, sf_dir):
    """Hourly series, error-bounded on its autocorrelation at 24 lags."""
    kept = thinning.thin_bounded(fixtures.hour_season(spark, sf_dir), 0.01, range(1, 25), hops="5log")
    return kept.select("series_id", "pos", F.round("value", 6).alias("value"), "n", "deviation")
