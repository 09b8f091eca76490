"""Queries of the methods themselves: statistics, thinning variants, baselines, measures, reconstruction, with SQL oracles."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..kernel.greedy import Rules
from ..operators import chunked, codecs, measures, reconstruct, series, statistics, thinning
from ..sources import fixtures as fx
from ..sources.tables import load_table as t

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


# -- series as SQL -------------------------------------------------------------------------------------------------------

CENT = "CAST(round(value * 100) AS BIGINT)"


def _grid(unit: str, n: int) -> str:
    return f"""(SELECT g.pos, e.c, e.n FROM (SELECT unnest(range({n})) AS pos) g LEFT JOIN (SELECT date_diff('{unit}', TIMESTAMP '2024-01-01', ts) AS pos,
      CAST(sum({CENT}) AS DOUBLE) AS c, count(*) AS n FROM events GROUP BY 1) e USING (pos))"""


DAY = f"(SELECT 'day_sum' AS series_id, pos, coalesce(c, 0) / 100.0::DOUBLE AS value FROM {_grid('day', 30)})"
HOUR = f"(SELECT 'hour_sum' AS series_id, pos, coalesce(c, 0) / 100.0::DOUBLE AS value FROM {_grid('hour', 720)})"
SEASON = f"(SELECT 'hour_season' AS series_id, pos, c / 100.0::DOUBLE / n + 60 * sin(2 * pi() * pos / 24.0::DOUBLE) AS value FROM {_grid('hour', 720)})"
MINUTE = f"(SELECT 'minute_sum' AS series_id, pos, coalesce(c, 0) / 100.0::DOUBLE AS value FROM {_grid('minute', 43200)})"
USERS = "(SELECT CAST(user_id AS VARCHAR) AS series_id, row_number() OVER (PARTITION BY user_id ORDER BY ts) - 1 AS pos, value FROM events)"
PART = "(SELECT 'part_price' AS series_id, row_number() OVER (ORDER BY p_partkey) - 1 AS pos, p_retailprice AS value FROM part)"
TYPES = """(WITH e AS (SELECT event_type, date_diff('hour', TIMESTAMP '2024-01-01', ts) AS pos, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS DOUBLE) / 100.0::DOUBLE / count(*) AS v FROM events GROUP BY 1, 2),
  j AS (SELECT k.event_type, g.pos, e.v FROM (SELECT DISTINCT event_type FROM events) k CROSS JOIN (SELECT unnest(range(720)) AS pos) g LEFT JOIN e ON e.event_type = k.event_type AND e.pos = g.pos),
  f AS (SELECT *, last_value(CASE WHEN v IS NOT NULL THEN pos END IGNORE NULLS) OVER (PARTITION BY event_type ORDER BY pos) AS a,
    first_value(CASE WHEN v IS NOT NULL THEN pos END IGNORE NULLS) OVER (PARTITION BY event_type ORDER BY pos ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS b FROM j)
  SELECT f.event_type AS series_id, f.pos, coalesce(f.v, x.v + (y.v - x.v) * ((f.pos - f.a) / (f.b - f.a)::DOUBLE), x.v, y.v)
    + 60 * sin(2 * pi() * (f.pos + 2 * (list_position(['click', 'error', 'purchase', 'signup', 'view'], f.event_type) - 1)) / 24.0::DOUBLE) AS value
  FROM f LEFT JOIN e x ON x.event_type = f.event_type AND x.pos = f.a LEFT JOIN e y ON y.event_type = f.event_type AND y.pos = f.b)"""


def lag_corr(src: str, lags: str) -> str:
    return f"""SELECT a.series_id, l.lag, round(CASE WHEN stddev_pop(a.value) > 0 AND stddev_pop(b.value) > 0 THEN corr(a.value, b.value) END, 6) AS r
    FROM s a JOIN (SELECT unnest({lags}) AS lag) l ON true JOIN s b ON a.series_id = b.series_id AND b.pos = a.pos + l.lag GROUP BY 1, 2""".replace("FROM s ", f"FROM {src} ", 1).replace("JOIN s b", f"JOIN {src} b")


def rounded(df, *cols, digits=6):
    return df.select(*[F.round(c, digits).alias(c) if c in cols else c for c in df.columns])


@query(f"SELECT series_id, pos, round(value, 6) AS value FROM {SEASON}")
def series_hour_season(spark, d):
    return rounded(fx.hour_season(spark, d), "value")


@query(f"SELECT series_id, pos, round(value, 6) AS value FROM {TYPES}")
def series_hour_season_type(spark, d):
    return rounded(fx.hour_season_type(spark, d), "value")


# -- statistics -----------------------------------------------------------------------------------------------------------


@query(f"""WITH s AS (SELECT * FROM {SEASON}), m AS (SELECT avg(value) AS m, var_pop(value) AS v FROM s)
SELECT a.series_id, l.lag, round(avg((a.value - m) * (b.value - m)) / any_value(v), 6) AS r FROM s a, m, (SELECT unnest(range(1, 25)) AS lag) l, s b WHERE b.pos = a.pos + l.lag GROUP BY 1, 2""")
def acf_global(spark, d):
    return rounded(statistics.autocorr(fx.hour_season(spark, d), list(range(1, 25)), "global"), "r").withColumn("lag", F.col("lag").cast("long"))


@query(lag_corr(SEASON, "range(1, 25)"))
def acf_pairs(spark, d):
    return rounded(statistics.autocorr(fx.hour_season(spark, d), list(range(1, 25))), "r").withColumn("lag", F.col("lag").cast("long"))


@query(lag_corr(USERS, "range(1, 6)"))
def acf_many_series(spark, d):
    return rounded(statistics.autocorr(fx.user_seq(spark, d), list(range(1, 6))), "r").withColumn("lag", F.col("lag").cast("long"))


@query(lag_corr(DAY, "[1, 2, 7]"))
def acf_chosen_lags(spark, d):
    return rounded(statistics.autocorr(fx.day_sum(spark, d), [1, 2, 7]), "r").withColumn("lag", F.col("lag").cast("long"))


@query(f"""WITH r AS ({lag_corr(TYPES, 'range(1, 4)').replace('round(CASE', '(CASE').replace('END, 6)', 'END)')}),
w AS (SELECT series_id, max(r) FILTER (WHERE lag = 1) AS a, max(r) FILTER (WHERE lag = 2) AS b, max(r) FILTER (WHERE lag = 3) AS c FROM r GROUP BY 1)
SELECT series_id, 1 AS lag, round(a, 6) AS r FROM w UNION ALL SELECT series_id, 2, round((b - a * a) / (1 - a * a), 6) FROM w
UNION ALL SELECT series_id, 3, round((a * a * a - 2 * a * b + a * b * b + c - a * a * c) / (1 + 2 * a * a * b - b * b - 2 * a * a), 6) FROM w""")
def pacf_recursion(spark, d):
    return rounded(statistics.partial_autocorr(fx.hour_season_type(spark, d), 3), "r")


_PS = f"""SELECT a.series_id, l.lag, count(*) AS n, sum(a.c) AS sx, sum(b.c) AS sy, sum(a.c * a.c) AS sxx, sum(b.c * b.c) AS syy, sum(a.c * b.c) AS sxy
FROM (SELECT series_id, pos, CAST(round(value * 100) AS BIGINT) AS c FROM {HOUR}) a, (SELECT unnest([1, 2, 24]) AS lag) l, (SELECT pos, CAST(round(value * 100) AS BIGINT) AS c FROM {HOUR}) b WHERE b.pos = a.pos + l.lag GROUP BY 1, 2"""


def _whole(spark, d):
    return fx.hour_sum(spark, d).withColumn("value", F.round(F.col("value") * 100).cast("long"))


@query(_PS)
def pair_sums(spark, d):
    return statistics.pair_sums(_whole(spark, d), [1, 2, 24])


@query(_PS)
def pair_sums_merged(spark, d):
    """The same from chunks of 100 positions and their overlaps."""
    return statistics.merge_pair_sums(statistics.chunk_pair_sums(_whole(spark, d), [1, 2, 24], 100)).select("series_id", "lag", "n", "sx", "sy", "sxx", "syy", "sxy")


def _win(agg):
    sql = {"mean": "avg", "sum": "sum", "min": "min", "max": "max"}[agg]
    src = f"(SELECT series_id, pos // 60 AS pos, CAST({sql}(value) AS DOUBLE) AS value FROM {MINUTE} GROUP BY 1, 2)"

    def f(spark, d):
        w = series.window_agg(fx.minute_sum(spark, d), 60, agg)
        return rounded(statistics.autocorr(w, list(range(1, 25))), "r").withColumn("lag", F.col("lag").cast("long"))

    f.__name__ = f"acf_windows_{agg}"
    query(lag_corr(src, "range(1, 25)"))(f)


for _a in ("mean", "sum", "min", "max"):
    _win(_a)


@query(f"SELECT series_id, pos // 7 AS pos, CAST(count(value) AS DOUBLE) AS value FROM {USERS} GROUP BY 1, 2 HAVING count(*) = 7")
def window_count(spark, d):
    return series.window_agg(fx.user_seq(spark, d), 7, "count")


@query(f"""WITH s AS (SELECT * FROM {HOUR}), t AS (SELECT *, value - lag(value) OVER (ORDER BY pos) AS step FROM s), r AS ({lag_corr(HOUR, 'range(1, 11)').replace('round(CASE', '(CASE').replace('END, 6)', 'END)')})
SELECT series_id, count(*) AS n, round(min(value), 6) AS least, round(max(value) - min(value), 6) AS range, round(quantile_cont(value, 0.5), 6) AS median, round(stddev_pop(value), 6) AS sd,
round(avg(CASE WHEN step > 0 THEN 1.0 WHEN step IS NOT NULL THEN 0.0 END), 6) AS up, round(avg(CASE WHEN step = 0 THEN 1.0 WHEN step IS NOT NULL THEN 0.0 END), 6) AS equal,
round(avg(CASE WHEN step < 0 THEN 1.0 WHEN step IS NOT NULL THEN 0.0 END), 6) AS down, round(avg(step), 6) AS mean_step,
round((SELECT r FROM r WHERE lag = 1), 6) AS acf1, round((SELECT sum(r) FROM r), 6) AS acf10 FROM t GROUP BY 1""")
def profile_features(spark, d):
    p = statistics.profile_series(fx.hour_sum(spark, d)).drop("pacf5")
    return rounded(p, *[c for c in p.columns if c not in ("series_id", "n")])


@query(f"""WITH s AS (SELECT * FROM {DAY}), c AS (SELECT pos AS gone, (lag(value) OVER (ORDER BY pos) + lead(value) OVER (ORDER BY pos)) / 2 AS line FROM s),
x AS (SELECT c.gone, s.pos, CASE WHEN s.pos = c.gone THEN c.line ELSE s.value END AS v FROM c, s WHERE c.line IS NOT NULL), l AS (SELECT unnest([1, 2, 3]) AS lag),
n AS (SELECT a.gone, lag, corr(a.v, b.v) AS r FROM x a, l, x b WHERE a.gone = b.gone AND b.pos = a.pos + lag GROUP BY 1, 2),
o AS (SELECT lag, corr(a.value, b.value) AS r FROM s a, l, s b WHERE b.pos = a.pos + lag GROUP BY 1)
SELECT 'day_sum' AS series_id, gone AS pos, round(avg(abs(n.r - o.r)), 8) AS impact FROM n JOIN o USING (lag) GROUP BY gone""")
def initial_impacts(spark, d):
    return rounded(statistics.initial_impacts(fx.day_sum(spark, d), [1, 2, 3]), "impact", digits=8)


@query()
def impact_skew(spark, d):
    return statistics.impact_skew(statistics.initial_impacts(fx.hour_season(spark, d), list(range(1, 25))))


# -- the flagship and its independent twin ----------------------------------------------------------------------------------


def _recursive(eps: float | None, keep: int | None) -> str:
    """The greedy as a recursive query: every step tries every inner point, redraws the line and recomputes the correlations."""
    stop = f"best.d <= {eps}" if eps is not None else f"best.k > {keep}"
    return f"""WITH RECURSIVE s AS MATERIALIZED (SELECT * FROM {DAY}), l AS (SELECT unnest([1, 2, 3]) AS lag),
o AS MATERIALIZED (SELECT lag, corr(a.value, b.value) AS r FROM s a, l, s b WHERE b.pos = a.pos + lag GROUP BY 1),
walk(step, pos, d) AS (
  SELECT 0, pos, 0.0::DOUBLE FROM s
  UNION ALL
  SELECT step + 1, pos, d FROM (
    WITH kept AS (SELECT step, pos FROM walk), size AS (SELECT count(*) AS k FROM kept),
    inner_ AS (SELECT pos AS gone FROM kept WHERE pos > 0 AND pos < 29),
    left_ AS (SELECT gone, kept.pos, lead(kept.pos) OVER (PARTITION BY gone ORDER BY kept.pos) AS nxt FROM inner_, kept WHERE kept.pos <> gone),
    x AS (SELECT left_.gone, g.pos, a.value + (coalesce(b.value, a.value) - a.value) * (g.pos - left_.pos) / coalesce(nxt - left_.pos, 1)::DOUBLE AS v
          FROM left_ JOIN s a ON a.pos = left_.pos LEFT JOIN s b ON b.pos = nxt JOIN s g ON g.pos >= left_.pos AND (g.pos < nxt OR (nxt IS NULL AND g.pos = left_.pos))),
    r AS (SELECT p.gone, lag, corr(p.v, q.v) AS r FROM x p, l, x q WHERE p.gone = q.gone AND q.pos = p.pos + lag GROUP BY 1, 2),
    best AS (SELECT gone, round(avg(abs(r.r - o.r)), 9) AS d, any_value(k) AS k FROM r JOIN o USING (lag), size GROUP BY gone ORDER BY 2, 1 LIMIT 1)
    SELECT kept.step, kept.pos, best.d FROM kept, best WHERE kept.pos <> best.gone AND {stop}) )
SELECT 'day_sum' AS series_id, pos, round(value, 6) AS value, round(d, 6) AS deviation FROM walk JOIN s USING (pos) WHERE step = (SELECT max(step) FROM walk)"""


@query(_recursive(0.05, None))
def thin_bounded_day(spark, d):
    k = thinning.thin_bounded(fx.day_sum(spark, d), 0.05, (1, 2, 3), hops="all")
    return rounded(k.select("series_id", "pos", "value", "deviation"), "value", "deviation")


@query(_recursive(None, 15))
def thin_to_ratio_day(spark, d):
    k = thinning.thin_to_ratio(fx.day_sum(spark, d), 2.0, (1, 2, 3), hops="all")
    return rounded(k.select("series_id", "pos", "value", "deviation"), "value", "deviation")


# -- variants and line baselines: (series_id, ends_kept, subset_ok, bound_ok) against constant truth -------------------------------


def _verified(name, source, source_sql, run, eps, lags, **check):
    def f(spark, d):
        s = source(spark, d)
        return measures.verify_bound(s, run(s).select("series_id", "pos", "value"), eps, list(lags), **check)

    f.__name__ = name
    query(f"SELECT DISTINCT series_id, true AS ends_kept, true AS subset_ok, true AS bound_ok FROM {source_sql}")(f)


L24, L5 = tuple(range(1, 25)), tuple(range(1, 6))
_B = lambda **k: lambda s: thinning.thin_bounded(s, 0.01, L24, **k)
for _h in ("1", "log", "3log", "5log", "10log", "15log", "half"):
    _verified(f"thin_hops_{_h}", fx.hour_season, SEASON, _B(hops=_h), 0.01, L24)
for _m, _e in (("rmse", 0.01), ("chebyshev", 0.02), ("mape", 0.05), ("range_rmse", 0.01)):
    _verified(f"thin_distance_{_m}", fx.hour_season, SEASON, lambda s, m=_m, e=_e: thinning.thin_bounded(s, e, L24, distance=m, hops="5log"), _e, L24, distance=_m)
_verified("thin_types", fx.hour_season_type, TYPES, _B(hops="5log"), 0.01, L24)
_verified("thin_users", fx.user_seq, USERS, lambda s: thinning.thin_bounded(s, 0.02, L5), 0.02, L5)
_verified("thin_partial", fx.hour_season_type, TYPES, lambda s: thinning.thin_bounded(s, 0.02, L5, statistic="partial", hops="5log"), 0.02, L5, statistic="partial")
_verified("thin_skip", fx.hour_season, SEASON, _B(hops="5log", on_violation="skip"), 0.01, L24)
_verified("thin_strict", fx.hour_season, SEASON, _B(hops="5log", strict=True), 0.01, L24)
_verified("thin_ratio_cap", fx.hour_season, SEASON, _B(max_ratio=3.0), 0.01, L24)
_verified("thin_chosen_lags", fx.hour_season, SEASON, lambda s: thinning.thin_bounded(s, 0.01, (1, 12, 24)), 0.01, (1, 12, 24))
_verified("thin_season_hops", fx.hour_season, SEASON, _B(hops="3log", hops_at_lags=(24,)), 0.01, L24)
for _a in ("mean", "sum", "max", "min"):
    _verified(f"thin_windows_{_a}", fx.hour_season_type, TYPES, lambda s, a=_a: thinning.thin_on_windows(s, 0.02, L5, 24, a, hops="0.5"), 0.02, L5, window=24, agg=_a)
_verified("thin_bulk", fx.user_seq, USERS, lambda s: chunked.thin_bulk(s, Rules(lags=L5, eps=0.02)), 0.02, L5)
_verified("thin_chunked", fx.hour_season_type, TYPES, lambda s: chunked.thin_chunked(s, Rules(lags=L24, eps=0.01, hops="log"), chunk=180), 0.01, L24)
_verified("thin_dispatched", fx.user_seq, USERS, lambda s: thinning.thin_any(s, Rules(lags=L5, eps=0.02)), 0.02, L5)
for _m in ("triangle_area", "turning_sum", "turning_err", "perceptual_vertical", "perceptual_euclidean"):
    _verified(f"line_{_m}", fx.hour_season_type, TYPES, lambda s, m=_m: thinning.thin(s, Rules(lags=L24, eps=0.01), m), 0.01, L24)


@query(f"SELECT DISTINCT series_id, true AS pinned_kept FROM {SEASON}")
def thin_pinned(spark, d):
    s = fx.hour_season(spark, d).withColumn("keep", F.col("value") > 120)
    k = thinning.thin_bounded(s, 0.05, L24, hops="log", pin="keep").select("series_id", "pos", F.lit(1).alias("k"))
    lost = F.count(F.when(F.col("keep") & F.col("k").isNull(), 1))
    return s.join(k, ["series_id", "pos"], "left").groupBy("series_id").agg((lost == 0).alias("pinned_kept"))  # true too where nothing is pinned


@query("SELECT 'types' AS series_id, true AS bound_ok")
def thin_multivariate(spark, d):
    s = fx.hour_season_type(spark, d).withColumn("type", F.col("series_id")).withColumn("series_id", F.lit("types"))
    wide = s.groupBy("series_id", "pos").pivot("type", ["click", "error", "purchase", "signup", "view"]).agg(F.first("value"))
    k = thinning.thin_multivariate(wide, ["click", "error", "purchase", "signup", "view"], Rules(lags=L24, eps=0.02, hops="log"))
    return k.groupBy("series_id").agg(((F.max("deviation") <= 0.02) & (F.count("*") < F.max("n"))).alias("bound_ok"))


@query(f"""WITH s AS (SELECT * FROM {HOUR}), a AS (SELECT *, sign(value - lag(value) OVER (ORDER BY pos)) AS up, sign(lead(value) OVER (ORDER BY pos) - value) AS dn FROM s),
b AS (SELECT *, last_value(nullif(up, 0) IGNORE NULLS) OVER (ORDER BY pos) AS was FROM a) SELECT series_id, pos, round(value, 6) AS value FROM b WHERE up IS NULL OR dn IS NULL OR (dn <> 0 AND was = -dn)""")
def turning_points_sql(spark, d):
    """First phase of the turning-point baseline in windows alone."""
    from pyspark.sql import Window

    w = Window.partitionBy("series_id").orderBy("pos")
    s = fx.hour_sum(spark, d).withColumn("up", F.signum(F.col("value") - F.lag("value").over(w))).withColumn("dn", F.signum(F.lead("value").over(w) - F.col("value")))
    s = s.withColumn("was", F.last(F.nullif("up", F.lit(0.0)), True).over(w))
    return rounded(s.where(F.col("up").isNull() | F.col("dn").isNull() | ((F.col("dn") != 0) & (F.col("was") == -F.col("dn")))).select("series_id", "pos", "value"), "value")


# -- reconstruction and queries on the kept form -------------------------------------------------------------------------------

KEPT4 = "(SELECT * FROM {s} WHERE pos % 4 = 0 OR pos = (SELECT max(pos) FROM {s} m))"


def _kept4(s):
    last = s.groupBy("series_id").agg(F.max("pos").alias("_hi"))
    return s.join(F.broadcast(last), "series_id").where("pos % 4 = 0 or pos = _hi").drop("_hi")


_REC = f"""s AS MATERIALIZED (SELECT * FROM {HOUR}), k AS (SELECT *, lead(pos) OVER (ORDER BY pos) AS nxt, lead(value) OVER (ORDER BY pos) AS nv FROM s WHERE pos % 4 = 0 OR pos = 719),
r AS (SELECT k.series_id, s.pos, k.value + coalesce((nv - k.value) * (s.pos - k.pos) / (nxt - k.pos)::DOUBLE, 0) AS value FROM k JOIN s ON s.pos >= k.pos AND s.pos < coalesce(nxt, k.pos + 1))"""


@query(f"WITH {_REC} SELECT series_id, pos, round(value, 6) AS value FROM r")
def reconstruct_lines(spark, d):
    return rounded(reconstruct.reconstruct(_kept4(fx.hour_sum(spark, d))), "value")


@query(f"WITH {_REC} SELECT series_id, pos, round(value, 6) AS value FROM r WHERE pos BETWEEN 101 AND 150")
def reconstruct_range(spark, d):
    return rounded(reconstruct.reconstruct(_kept4(fx.hour_sum(spark, d)), between=(101, 150)), "value")


@query(f"WITH {_REC} SELECT series_id, pos, round(value, 6) AS value FROM r WHERE pos % 7 = 3")
def value_at_points(spark, d):
    s = fx.hour_sum(spark, d)
    return rounded(reconstruct.value_at(_kept4(s), s.where("pos % 7 = 3").select("series_id", "pos")), "value")


@query(f"WITH {_REC} SELECT series_id, count(*) AS n, round(sum(value), 4) AS total, round(avg(value), 6) AS mean, round(min(value), 6) AS least, round(max(value), 6) AS greatest, round(avg(value * value), 3) AS second_moment FROM r GROUP BY 1")
def piecewise_aggregates(spark, d):
    p = reconstruct.piecewise_agg(_kept4(fx.hour_sum(spark, d)))
    return p.select("series_id", "n", F.round("total", 4).alias("total"), *[F.round(c, 6).alias(c) for c in ("mean", "least", "greatest")], F.round("second_moment", 3).alias("second_moment"))


# -- measures ----------------------------------------------------------------------------------------------------------------------


def _valued(s):
    """Positions that hold a value. Counts of all positions of a grid would not need its values, and the table would not be read."""
    return s.where("value is not null")


@query(f"WITH {_REC} SELECT 'hour_sum' AS series_id, 720 AS n, count(*) AS n_kept, round(720.0 / count(*), 6) AS ratio FROM k")
def measure_ratio(spark, d):
    s = _valued(fx.hour_sum(spark, d))
    return rounded(measures.compression_ratio(s, _kept4(s)), "ratio")


@query(f"WITH {_REC} SELECT 'hour_sum' AS series_id, round(count(*) * 64.0 / 720, 6) AS bits, round(count(*) * 96.0 / 720, 6) AS bits_with_positions FROM k")
def measure_bits(spark, d):
    s = _valued(fx.hour_sum(spark, d))
    return rounded(measures.bits_per_value(s, _kept4(s)), "bits", "bits_with_positions")


@query(f"""WITH {_REC}, e AS (SELECT s.value AS x, r.value - s.value AS e FROM s JOIN r USING (pos))
SELECT 'hour_sum' AS series_id, round(avg(abs(e)), 6) AS mae, round(avg(e * e), 4) AS mse, round(sqrt(avg(e * e)), 6) AS rmse, round(sqrt(avg(e * e)) / (max(x) - min(x)), 6) AS range_rmse,
round(max(abs(e)), 6) AS chebyshev, round(avg(abs(e) / abs(x)), 6) AS mape, round(20 * log10((max(x) - min(x)) / sqrt(avg(e * e))), 6) AS psnr, round(sqrt(sum(e * e)) / count(*), 6) AS rmse_as_printed FROM e""")
def measure_errors(spark, d):
    s = fx.hour_sum(spark, d)
    e = measures.errors(s, reconstruct.reconstruct(_kept4(s)), as_printed=True)
    return e.select("series_id", *[F.round(c, 4 if c == "mse" else 6).alias(c) for c in e.columns if c != "series_id"])


@query(f"""WITH {_REC}, m AS (SELECT i.pos, avg(j.value) AS m FROM s i JOIN s j ON j.pos < i.pos GROUP BY 1), p AS (SELECT m.pos, avg(abs(j.value - m)) AS sp FROM m JOIN s j ON j.pos < m.pos GROUP BY 1)
SELECT 'hour_sum' AS series_id, round(sum(abs(s.value - r.value) / (abs(s.value + r.value) / 2 + coalesce(sp, 0))) / count(*), 6) AS msmape FROM s JOIN r USING (pos) LEFT JOIN p USING (pos)""")
def measure_msmape(spark, d):
    s = fx.hour_sum(spark, d)
    return rounded(measures.msmape(s, reconstruct.reconstruct(_kept4(s))), "msmape")


@query(f"""WITH {_REC}, l AS (SELECT unnest(range(1, 25)) AS lag), a AS (SELECT lag, corr(x.value, y.value) AS r FROM s x, l, s y WHERE y.pos = x.pos + lag GROUP BY 1),
b AS (SELECT lag, corr(x.value, y.value) AS r FROM r x, l, r y WHERE y.pos = x.pos + lag GROUP BY 1) SELECT 'hour_sum' AS series_id, round(avg(abs(a.r - b.r)), 6) AS deviation FROM a JOIN b USING (lag)""")
def measure_deviation(spark, d):
    s = fx.hour_sum(spark, d)
    return rounded(measures.deviation(s, reconstruct.reconstruct(_kept4(s)), list(range(1, 25))), "deviation")


@query(f"SELECT series_id, pos, round(avg(value) OVER (ORDER BY pos), 6) AS prefix_mean FROM {HOUR}")
def measure_prefix_mean(spark, d):
    return rounded(measures.prefix_mean(fx.hour_sum(spark, d)), "prefix_mean")


# -- codecs ------------------------------------------------------------------------------------------------------------------------


def _within(name, codec, tol):
    def f(spark, d):
        s = fx.user_seq(spark, d)
        y = codecs.draw_segments(codecs.segments(s, codec, tol))
        return measures.errors(s, y).join(s.groupBy("series_id").count(), "series_id").select("series_id", (F.col("chebyshev") <= tol + 1e-9).alias("within"), F.col("count").alias("n"))

    f.__name__ = name
    query(f"SELECT series_id, true AS within, count(*) AS n FROM {USERS} GROUP BY 1")(f)


_within("codec_pmc", "pmc", 10.0)
_within("codec_swing", "swing", 10.0)
_within("codec_sim_piece", "sim_piece", 10.0)


@query(f"""WITH RECURSIVE s AS MATERIALIZED (SELECT * FROM {HOUR}), walk(pos, start, n, total, lo, hi) AS (
SELECT pos, pos, 1::BIGINT, value, value, value FROM s WHERE pos = 0 UNION ALL
SELECT s.pos, CASE WHEN new THEN s.pos ELSE w.start END, CASE WHEN new THEN 1 ELSE w.n + 1 END, CASE WHEN new THEN s.value ELSE w.total + s.value END,
CASE WHEN new THEN s.value ELSE least(w.lo, s.value) END, CASE WHEN new THEN s.value ELSE greatest(w.hi, s.value) END
FROM walk w JOIN s ON s.pos = w.pos + 1, LATERAL (SELECT greatest(w.hi, s.value) - (w.total + s.value) / (w.n + 1) > 150 OR (w.total + s.value) / (w.n + 1) - least(w.lo, s.value) > 150 AS new) q)
SELECT 'hour_sum' AS series_id, start AS start_pos, max(n) AS length, round(arg_max(total, n) / max(n), 6) AS intercept FROM walk GROUP BY start""")
def codec_pmc_pieces(spark, d):
    return rounded(codecs.segments(fx.hour_sum(spark, d), "pmc", 150.0).select("series_id", "start_pos", "length", "intercept"), "intercept")


@query("SELECT DISTINCT 'day_qty' AS series_id, true AS within FROM part")
def codec_merged_cones_sql(spark, d):
    """Cone pieces from the kernel, merged in SQL windows, drawn without Python."""
    s = fx.day_qty(spark, d)
    y = codecs.draw_segments(codecs.merge_slopes(codecs.cone_segments(s, 100.0)))
    return measures.errors(s, y).select("series_id", (F.col("chebyshev") <= 100.0 + 1e-9).alias("within"))


def _lossless(codec):
    def f(spark, d):
        s = fx.user_seq(spark, d)
        y = codecs.xor_decode(codecs.xor_encode(s, codec), codec)
        return s.join(y.withColumnRenamed("value", "y"), ["series_id", "pos"], "left").groupBy("series_id").agg(F.count("*").alias("n"), F.min(F.coalesce(F.col("value") == F.col("y"), F.lit(False))).alias("equal"))

    f.__name__ = f"codec_{codec}"
    query(f"SELECT series_id, count(*) AS n, true AS equal FROM {USERS} GROUP BY 1")(f)


_lossless("gorilla")
_lossless("chimp")


@query("SELECT 'hour_season' AS series_id, true AS equal")
def codec_fourier_all(spark, d):
    s = fx.hour_season(spark, d)
    e = measures.errors(s, codecs.inverse_fourier(codecs.fourier(s, 361)))
    return e.select("series_id", (F.col("chebyshev") < 1e-9).alias("equal"))


@query(f"SELECT 0 AS k, round(sum(value), 4) AS re FROM {SEASON} UNION ALL SELECT 30, round(sum(value * cos(2 * pi() * 30 * pos / 720.0::DOUBLE)), 4) FROM {SEASON}")
def codec_fourier_largest(spark, d):
    return codecs.fourier(fx.hour_season(spark, d), 2, "largest").select("k", F.round("re", 4).alias("re"))


@query(f"SELECT series_id, pos, round(round(value / 5.0) * 5.0, 6) AS value FROM {USERS}")
def codec_quantize(spark, d):
    return rounded(codecs.quantize(fx.user_seq(spark, d), 5.0), "value")


@query("SELECT CAST(event_id AS BIGINT) AS pos FROM (SELECT row_number() OVER (ORDER BY event_id) - 1 AS event_id FROM events) WHERE event_id % 10 = 0")
def baseline_every_kth(spark, d):
    return fx.events_raw(spark, d).where("pos % 10 = 0").select("pos")


@query(f"SELECT series_id, count(*) AS n FROM {TYPES} GROUP BY 1")
def baseline_identity(spark, d):
    return fx.hour_season_type(spark, d).groupBy("series_id").agg(F.count("*").alias("n"))


# -- shaping ------------------------------------------------------------------------------------------------------------------------


@query("SELECT 'events_raw#' || (pos // 1000) AS series_id, pos % 1000 AS pos, value FROM (SELECT row_number() OVER (ORDER BY event_id) - 1 AS pos, value FROM events)")
def segment_fixed(spark, d):
    return series.segment(fx.events_raw(spark, d), 1000)


@query(f"SELECT series_id, pos, value FROM {USERS} QUALIFY row_number() OVER (PARTITION BY series_id ORDER BY pos DESC) <= 5")
def holdout_last(spark, d):
    return series.holdout(fx.user_seq(spark, d), 5)[1]


@query("""WITH g AS (SELECT unnest(range(43200)) AS pos), e AS (SELECT date_diff('minute', TIMESTAMP '2024-01-01', ts) AS pos, count(*) AS n FROM events GROUP BY 1)
SELECT 'minute_count' AS series_id, pos, CAST(coalesce(n, 0) AS DOUBLE) AS value FROM g LEFT JOIN e USING (pos)""")
def to_grid_zero(spark, d):
    return fx.minute_count(spark, d)


@query("""WITH g AS (SELECT unnest(range(43200)) AS pos), e AS (SELECT date_diff('minute', TIMESTAMP '2024-01-01', ts) AS pos, count(*) AS n FROM events GROUP BY 1), j AS (SELECT pos, n FROM g LEFT JOIN e USING (pos))
SELECT 'minute_count' AS series_id, pos, CAST(last_value(n IGNORE NULLS) OVER (ORDER BY pos) AS DOUBLE) AS value FROM j""")
def to_grid_ffill(spark, d):
    return series.fill(fx.minute_count(spark, d).withColumn("value", F.nullif("value", F.lit(0.0))), "ffill")


@query("""WITH g AS (SELECT unnest(range(43200)) AS pos), e AS (SELECT date_diff('minute', TIMESTAMP '2024-01-01', ts) AS pos, count(*) AS n FROM events GROUP BY 1), j AS (SELECT pos, n FROM g LEFT JOIN e USING (pos)),
k AS (SELECT pos, n, last_value(CASE WHEN n IS NOT NULL THEN pos END IGNORE NULLS) OVER (ORDER BY pos) AS a, first_value(CASE WHEN n IS NOT NULL THEN pos END IGNORE NULLS) OVER (ORDER BY pos ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS b FROM j)
SELECT 'minute_count' AS series_id, k.pos, round(coalesce(CAST(k.n AS DOUBLE), x.n + (y.n - x.n) * (k.pos - a) / (b - a)::DOUBLE, x.n, y.n), 6) AS value FROM k LEFT JOIN e x ON x.pos = a LEFT JOIN e y ON y.pos = b""")
def to_grid_linear(spark, d):
    return rounded(series.fill(fx.minute_count(spark, d).withColumn("value", F.nullif("value", F.lit(0.0))), "linear"), "value")


@query("SELECT date_trunc('hour', ts) AS h, count(*) AS n FROM events GROUP BY 1")
def resample_window(spark, d):
    return t(spark, d, "events").groupBy(F.window("ts", "1 hour")["start"].alias("h")).agg(F.count("*").alias("n"))


@query("SELECT vec_id::VARCHAR AS series_id, count(*) AS n FROM (SELECT vec_id, unnest(embedding) FROM embeddings) GROUP BY 1")
def series_from_arrays(spark, d):
    return fx.embed_dims(spark, d).groupBy("series_id").agg(F.count("*").alias("n"))


INF = math.inf
