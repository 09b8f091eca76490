"""Statistics in DataFrame form: pair sums, autocorrelation, partial autocorrelation, impacts, profiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

KEY = "series_id"


def pair_sums(df: DataFrame, lags: list[int], key: str = KEY) -> DataFrame:
    """``(key, lag, n, sx, sy, sxx, syy, sxy)``: the running sums of all pairs a lag apart. One sort per key, one pass."""
    w = Window.partitionBy(key).orderBy("pos")
    later = F.array(*[F.struct(F.lit(l).alias("lag"), F.lead("value", l).over(w).alias("y")) for l in lags])
    p = df.select(key, F.col("value").alias("x"), later.alias("later")).select(key, "x", F.inline("later")).where("y is not null")
    return p.groupBy(key, "lag").agg(
        F.count("*").alias("n"), F.sum("x").alias("sx"), F.sum("y").alias("sy"), F.sum(F.col("x") * F.col("x")).alias("sxx"),
        F.sum(F.col("y") * F.col("y")).alias("syy"), F.sum(F.col("x") * F.col("y")).alias("sxy"),
    )


def merge_pair_sums(parts: DataFrame, key: str = KEY) -> DataFrame:
    """Sums of parts of a series (chunks and the overlaps between them) add up to the sums of the whole."""
    names = ["n", "sx", "sy", "sxx", "syy", "sxy"]
    return parts.groupBy(key, "lag").agg(*[F.sum(c).alias(c) for c in names])


def chunk_pair_sums(df: DataFrame, lags: list[int], chunk: int, key: str = KEY) -> DataFrame:
    """Pair sums per chunk of positions, the pairs that reach into the next chunk included; chunks never hold each other's rows.

    The first ``max(lags)`` values of a chunk are sent to the chunk before it as a halo.
    """
    reach = max(lags)
    home = df.withColumn("chunk", F.floor(F.col("pos") / chunk).cast("long")).withColumn("own", F.lit(True))
    halo = home.where((F.col("chunk") > 0) & (F.col("pos") % chunk < reach)).withColumn("chunk", F.col("chunk") - 1).withColumn("own", F.lit(False))
    both = home.unionByName(halo)
    w = Window.partitionBy(key, "chunk").orderBy("pos")
    later = F.array(*[F.struct(F.lit(l).alias("lag"), F.lead("value", l).over(w).alias("y")) for l in lags])
    p = both.select(key, "chunk", "own", F.col("value").alias("x"), later.alias("later")).where("own").select(key, "chunk", "x", F.inline("later")).where("y is not null")
    return p.groupBy(key, "chunk", "lag").agg(
        F.count("*").alias("n"), F.sum("x").alias("sx"), F.sum("y").alias("sy"), F.sum(F.col("x") * F.col("x")).alias("sxx"),
        F.sum(F.col("y") * F.col("y")).alias("syy"), F.sum(F.col("x") * F.col("y")).alias("sxy"),
    )


def r_of(n, sx, sy, sxx, syy, sxy) -> Column:
    vx, vy = n * sxx - sx * sx, n * syy - sy * sy
    return F.when((vx > 1e-12 * n * sxx) & (vy > 1e-12 * n * syy), (n * sxy - sx * sy) / F.sqrt(vx * vy))


def autocorr(df: DataFrame, lags: list[int], form: str = "pairs", key: str = KEY) -> DataFrame:
    """``(key, lag, r)``. ``pairs``: Pearson correlation of the pairs; ``global``: one mean and variance for all; null where undefined."""
    w = Window.partitionBy(key)
    centred = df.select(key, "pos", (F.col("value") - F.avg("value").over(w)).alias("value"))
    s = pair_sums(centred, lags, key)
    if form == "pairs":
        return s.select(key, "lag", r_of(*[F.col(c) for c in ("n", "sx", "sy", "sxx", "syy", "sxy")]).alias("r"))
    var = centred.groupBy(key).agg(F.avg(F.col("value") * F.col("value")).alias("_v"))
    return s.join(var, key).select(key, "lag", F.try_divide(F.col("sxy") / F.col("n"), F.col("_v")).alias("r"))


def partial_of(r: Column) -> Column:
    """Partial autocorrelations of an array of autocorrelations, by the order recursion in array functions."""
    zero = F.struct(F.array().cast("array<double>").alias("phi"), F.array().cast("array<double>").alias("out"))

    def dot(a, b):
        return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)

    def step(s, x):
        k = F.size(s["out"])
        known = F.slice(r, 1, F.greatest(k, F.lit(0)))
        back = F.reverse(known)
        p = F.when(k == 0, x).otherwise((x - dot(s["phi"], back)) / (1 - dot(s["phi"], known)))
        phi = F.concat(F.zip_with(s["phi"], F.reverse(s["phi"]), lambda a, b: a - p * b), F.array(p))
        return F.struct(phi.alias("phi"), F.concat(s["out"], F.array(p)).alias("out"))

    return F.aggregate(r, zero, step, lambda s: s["out"])


def partial_autocorr(df: DataFrame, lags: int, key: str = KEY) -> DataFrame:
    r = autocorr(df, list(range(1, lags + 1)), "pairs", key)
    arr = r.groupBy(key).agg(F.transform(F.array_sort(F.collect_list(F.struct("lag", "r"))), lambda x: x["r"]).alias("rs"))
    return arr.select(key, F.posexplode(partial_of(F.col("rs"))).alias("i", "r")).select(key, (F.col("i") + 1).alias("lag"), "r")


def initial_impacts(df: DataFrame, lags: list[int], key: str = KEY) -> DataFrame:
    """``(key, pos, impact)``: mean absolute change of the autocorrelation if the point alone were drawn as the mean of its neighbours.

    One point changes five sums per lag by closed forms, so no series is rebuilt. Ends have no row.
    """
    w = Window.partitionBy(key).orderBy("pos")
    whole = Window.partitionBy(key)
    s = df.select(key, "pos", (F.col("value") - F.avg("value").over(whole)).alias("x"), F.count("*").over(whole).alias("size"))
    s = s.withColumn("d", (F.lag("x").over(w) + F.lead("x").over(w)) / 2 - F.col("x"))
    around = F.array(*[F.struct(F.lit(l).alias("lag"), F.coalesce(F.lag("x", l).over(w), F.lit(0.0)).alias("before"), F.coalesce(F.lead("x", l).over(w), F.lit(0.0)).alias("after")) for l in lags])
    s = s.select(key, "pos", "x", "d", "size", around.alias("around")).where("d is not null").select(key, "pos", "x", "d", "size", F.inline("around"))
    sums = pair_sums(df.select(key, "pos", (F.col("value") - F.avg("value").over(whole)).alias("value")), lags, key)
    j = s.join(sums, [key, "lag"])
    early, late = F.col("pos") < F.col("size") - F.col("lag"), F.col("pos") >= F.col("lag")
    d, sq = F.col("d"), 2 * F.col("x") * F.col("d") + F.col("d") * F.col("d")
    on = lambda c, v: F.when(c, v).otherwise(0.0)
    new = r_of(F.col("n"), F.col("sx") + on(early, d), F.col("sy") + on(late, d), F.col("sxx") + on(early, sq), F.col("syy") + on(late, sq), F.col("sxy") + d * (F.col("before") + F.col("after")))
    old = r_of(*[F.col(c) for c in ("n", "sx", "sy", "sxx", "syy", "sxy")])
    return j.select(key, "pos", F.abs(new - old).alias("a")).groupBy(key, "pos").agg(F.avg("a").alias("impact"))


def impact_skew(impacts: DataFrame, key: str = KEY) -> DataFrame:
    """``(key, pos, impact, share_of_points, share_of_impact)``: cumulative shares in order of impact."""
    w = Window.partitionBy(key).orderBy("impact", "pos")
    run = F.sum("impact").over(w.rowsBetween(Window.unboundedPreceding, 0))
    total = F.sum("impact").over(Window.partitionBy(key))
    return impacts.select(key, "pos", "impact", F.cume_dist().over(w).alias("share_of_points"), F.try_divide(run, total).alias("share_of_impact"))


def profile_series(df: DataFrame, key: str = KEY, squared: bool = False) -> DataFrame:
    """Length, correlations (lag 1, sum of ten, partial sum of five), extremes, median, deviation, shares of ups, equals and downs, mean step."""
    w = Window.partitionBy(key).orderBy("pos")
    s = df.withColumn("step", F.col("value") - F.lag("value").over(w))
    basic = s.groupBy(key).agg(
        F.count("*").alias("n"), F.min("value").alias("least"), (F.max("value") - F.min("value")).alias("range"), F.percentile("value", 0.5).alias("median"),
        F.stddev_pop("value").alias("sd"), F.avg(F.when(F.col("step") > 0, 1.0).when(F.col("step").isNotNull(), 0.0)).alias("up"),
        F.avg(F.when(F.col("step") == 0, 1.0).when(F.col("step").isNotNull(), 0.0)).alias("equal"),
        F.avg(F.when(F.col("step") < 0, 1.0).when(F.col("step").isNotNull(), 0.0)).alias("down"), F.avg("step").alias("mean_step"),
    )
    r = autocorr(df, list(range(1, 11)), "pairs", key)
    rs = r.groupBy(key).agg(F.transform(F.array_sort(F.collect_list(F.struct("lag", "r"))), lambda x: x["r"]).alias("rs"))
    power = (lambda x: x * x) if squared else (lambda x: x)
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + power(x))
    rs = rs.select(key, F.element_at("rs", 1).alias("acf1"), total(F.col("rs")).alias("acf10"), total(F.slice(partial_of(F.col("rs")), 1, 5)).alias("pacf5"))
    return basic.join(rs, key)
