"""Registered queries against their SQL twins on the middle tables."""

from __future__ import annotations

import pytest
from conftest import MIDDLE, SMALL, same_rows

import __spark_entry__
from tsthin import catalog

CHEAP = [
    *[n for n in catalog.relational.ORACLES if not n.startswith("roundtrip_")],
    "acf_pairs", "acf_global", "pacf_recursion", "pair_sums_merged", "acf_windows_mean", "initial_impacts", "thin_bounded_day", "thin_to_ratio_day",
    "thin_windows_max", "thin_partial", "line_triangle_area", "line_perceptual_vertical", "turning_points_sql", "reconstruct_lines", "value_at_points", "piecewise_aggregates",
    "measure_errors", "measure_msmape", "measure_deviation", "codec_pmc_pieces", "codec_gorilla", "codec_chimp", "to_grid_linear", "udf_grouped_agg", "udtf_thin",
    "read_thinned_source", "st_watermark_late", "st_stateful_thin", "forecast_seasonal_naive",
]


@pytest.mark.parametrize("name", CHEAP)
def test_twin(spark, duck, name):
    same_rows(catalog.queries()[name](spark, MIDDLE), duck.execute(catalog.oracles()[name]))


def test_entry_and_names(spark):
    assert __spark_entry__.entry(spark).count() > 2
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_smallest_tables(spark):
    q = catalog.queries()
    for name in ("thin_types", "w2_importance_skew", "acf_many_series", "w20_many_series"):
        assert q[name](spark, SMALL).count() > 0


def test_workloads_take_all_lengths_and_ratios(spark, monkeypatch):
    from tsthin.plans import workloads

    class Seen(Exception):
        pass

    def see(*args, **named):
        raise Seen(*args[1:])

    monkeypatch.setattr(workloads.anomaly, "discords", see)
    for q in (workloads.anomaly_discords, workloads.w18_anomaly):
        with pytest.raises(Seen) as e:
            q(spark, SMALL)
        assert list(e.value.args[0]) == list(range(75, 126))
    monkeypatch.setattr(workloads, "_forecast_sweep", see)
    with pytest.raises(Seen) as e:
        workloads.w15_exp1(spark, SMALL)
    assert {f"{m} {r}" for m in ("mae", "chebyshev", "triangle_area", "turning_sum", "perceptual_vertical") for r in range(2, 11)} <= set(e.value.args[1])
