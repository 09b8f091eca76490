"""Registered queries on tables that the middle ones do not stand for: ties, nothing to pin, columns that could be pruned."""

from __future__ import annotations

import duckdb
import pytest
from conftest import MIDDLE, same_rows

from tsthin import catalog


def events(spark, tmp_path, rows) -> str:
    """A folder with an events table of ``(ts, user_id, value)``."""
    df = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "event_id long, ts string, user_id long, value double")
    df.selectExpr("event_id", "CAST(ts AS timestamp_ntz) AS ts", "user_id", "'view' AS event_type", "value", "'' AS props").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    return str(tmp_path)


def test_values_that_tie_with_the_model_are_not_above_it(spark, tmp_path):
    values = [75.47, 0.21, 39.34]  # 39.34 is the mean and one; in double precision the mean comes out less
    assert values[2] > (values[0] + values[1] + values[2]) / 3 + 1
    d = events(spark, tmp_path, [(f"2024-01-01 00:00:0{i}", 1, v) for i, v in enumerate(values)])
    got = catalog.queries()["grouped_map_cogroup"](spark, d).collect()
    assert [(r["series_id"], r["above"]) for r in got] == [("1", 1)]


def test_pins_hold_where_nothing_is_pinned(spark, tmp_path):
    d = events(spark, tmp_path, [(f"2024-01-{1 + h // 24:02d} {h % 24:02d}:00:00", 1, 5.0 + h % 7) for h in range(720)])
    with duckdb.connect() as c:
        c.execute(f"CREATE VIEW events AS SELECT * FROM '{d}/events.parquet/*.parquet'")
        same_rows(catalog.queries()["thin_pinned"](spark, d), c.execute(catalog.oracles()["thin_pinned"]))


@pytest.mark.parametrize("name", ["measure_ratio", "measure_bits"])
def test_measures_read_their_table(spark, duck, name):
    df = catalog.queries()[name](spark, MIDDLE)
    assert "events.parquet" in df._jdf.queryExecution().optimizedPlan().toString() + df._jdf.queryExecution().executedPlan().toString()
    same_rows(df, duck.execute(catalog.oracles()[name]))
