"""Surrounding relational queries: what users of series need around them. Each has a DataFrame form and its SQL twin."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

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


def money(c: str):
    return F.round(F.col(c) * 100).cast("long")


M = lambda c: f"CAST(round({c} * 100) AS BIGINT)"


# -- scans and sinks ----------------------------------------------------------------------------------------------------


@query("SELECT event_id, event_type, value FROM events")
def scan_pruned(spark, d):
    return t(spark, d, "events").select("event_id", "event_type", "value")


@query("SELECT event_id, value FROM events WHERE ts >= TIMESTAMP '2024-01-10' AND ts < TIMESTAMP '2024-01-12'")
def scan_filtered_range(spark, d):
    e = t(spark, d, "events")
    lit = lambda x: F.lit(x).cast("timestamp_ntz")
    return e.where((F.col("ts") >= lit("2024-01-10")) & (F.col("ts") < lit("2024-01-12"))).select("event_id", "value")


def _scratch(spark: SparkSession) -> str:
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="checkpoints-"))
    return f"{sc._jsc.sc().getCheckpointDir().get()}/roundtrip-{uuid.uuid4().hex}"


ROUND = "SELECT p_partkey, p_name, p_retailprice FROM part"


def _roundtrip(kind):
    def f(spark, d):
        df = t(spark, d, "part").select("p_partkey", "p_name", "p_retailprice")
        path = _scratch(spark)
        df.write.format(kind).save(path)
        return spark.read.schema(df.schema).format(kind).load(path)

    f.__name__ = f"roundtrip_{kind}"
    return query(ROUND)(f)


for _k in ("parquet", "csv", "json", "orc"):
    _roundtrip(_k)


# -- projections and predicates -------------------------------------------------------------------------------------------


@query(f"SELECT l_orderkey, l_linenumber, {M('l_extendedprice * (1 - l_discount)')} AS cents FROM lineitem")
def project_arith(spark, d):
    return t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")) * 100).cast("long").alias("cents"))


@query("SELECT o_orderkey, CASE WHEN o_totalprice < 50000 THEN 'low' WHEN o_totalprice < 200000 THEN 'mid' ELSE 'high' END AS bucket FROM orders")
def case_bucket(spark, d):
    p = F.col("o_totalprice")
    return t(spark, d, "orders").select("o_orderkey", F.when(p < 50000, "low").when(p < 200000, "mid").otherwise("high").alias("bucket"))


@query("SELECT l.doc_id, (l.toxic IS NOT DISTINCT FROM NULLIF(l.quality, 1)) AS same FROM labels l")
def null_safe_eq(spark, d):
    return t(spark, d, "labels").select("doc_id", F.col("toxic").eqNullSafe(F.nullif("quality", F.lit(1))).alias("same"))


@query("SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderkey BETWEEN 100 AND 5000")
def in_list(spark, d):
    return t(spark, d, "orders").where(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_orderkey").between(100, 5000)).select("o_orderkey")


@query("SELECT p_partkey, p_name FROM part WHERE p_name LIKE 'red%'")
def like_prefix(spark, d):
    return t(spark, d, "part").where(F.col("p_name").like("red%")).select("p_partkey", "p_name")


@query("SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{4}')")
def rlike_regex(spark, d):
    return t(spark, d, "documents").where(F.col("text").rlike("[0-9]{4}")).select("doc_id")


# -- joins ----------------------------------------------------------------------------------------------------------------

_OL = "SELECT o.o_orderstatus, count(*) AS n, sum(CAST(l.l_quantity AS BIGINT)) AS qty FROM orders o JOIN lineitem l ON o.o_orderkey = l.l_orderkey GROUP BY 1"


def _order_lines(spark, d, hint):
    o, li = t(spark, d, "orders").select("o_orderkey", "o_orderstatus"), t(spark, d, "lineitem").select("l_orderkey", "l_quantity")
    return o.hint(hint).join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"))


@query(_OL)
def join_inner_hash(spark, d):
    return _order_lines(spark, d, "shuffle_hash")


@query(_OL)
def join_sort_merge(spark, d):
    return _order_lines(spark, d, "merge")


@query("SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def join_broadcast_dims(spark, d):
    n, r = t(spark, d, "nation"), t(spark, d, "region")
    return t(spark, d, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


def _outer(kind, sql):
    def f(spark, d):
        c, o = t(spark, d, "customer").select("c_custkey"), t(spark, d, "orders").where("o_totalprice > 100000").select("o_custkey", "o_orderkey")
        return c.join(o, F.col("c_custkey") == F.col("o_custkey"), kind).groupBy(F.col("c_custkey").isNull().alias("no_customer")).agg(F.count("*").alias("n"), F.count("o_orderkey").alias("orders"))

    f.__name__ = f"join_{kind}"
    query(f"SELECT c_custkey IS NULL AS no_customer, count(*) AS n, count(o_orderkey) AS orders FROM customer {sql} JOIN (SELECT * FROM orders WHERE o_totalprice > 100000) o ON c_custkey = o_custkey GROUP BY 1")(f)


for _k in ("left", "right", "full"):
    _outer(_k, _k.upper())


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def join_semi(spark, d):
    o = t(spark, d, "orders").where("o_totalprice > 300000")
    return t(spark, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
def join_anti(spark, d):
    urgent = t(spark, d, "orders").where(F.col("o_orderpriority") == "1-URGENT")
    return t(spark, d, "customer").join(urgent, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("SELECT event_type, lag, count(*) AS n FROM events CROSS JOIN (VALUES (1), (7), (24)) l(lag) WHERE event_id % lag = 0 GROUP BY 1, 2")
def join_cross_lags(spark, d):
    lags = F.explode(F.array(F.lit(1), F.lit(7), F.lit(24))).alias("lag")
    return t(spark, d, "events").select("event_type", "event_id", lags).where(F.col("event_id") % F.col("lag") == 0).groupBy("event_type", "lag").agg(F.count("*").alias("n"))


@query("""WITH s AS (SELECT k AS seg, k * 300 AS lo, k * 300 + 100 + k % 150 AS hi FROM range(0, 60) r(k))
SELECT seg, count(*) AS n FROM s JOIN events ON event_id BETWEEN lo AND hi GROUP BY 1""")
def join_range_segments(spark, d):
    """Positions within segment bounds, met through bins of the segment length, so that no nested loop is needed."""
    width = 256
    seg = spark.range(60).select(F.col("id").alias("seg"), (F.col("id") * 300).alias("lo"), (F.col("id") * 300 + 100 + F.col("id") % 150).alias("hi"))
    bins = seg.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    e = t(spark, d, "events").select("event_id", F.floor(F.col("event_id") / width).alias("bin"))
    return e.join(bins, "bin").where(F.col("event_id").between(F.col("lo"), F.col("hi"))).groupBy("seg").agg(F.count("*").alias("n"))


@query("SELECT event_id, (event_id // 7) * 7 AS kept_pos FROM events")
def join_asof_kept(spark, d):
    e = t(spark, d, "events").select("event_id")
    rows = e.withColumn("k", F.when(F.col("event_id") % 7 == 0, F.col("event_id"))).withColumn("part", F.floor(F.col("event_id") / 7000))
    w = Window.partitionBy("part").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    return rows.select("event_id", F.last("k", True).over(w).alias("kept_pos"))


@query("""SELECT a.event_id, count(*) AS near FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type = 'click'
AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR GROUP BY 1""")
def join_interval_events(spark, d):
    e = t(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("u"))
    hour = 3_600_000_000
    a = e.where("event_type = 'purchase'").withColumn("bin", F.explode(F.array(*[F.floor(F.col("u") / hour) + k for k in (-1, 0, 1)])))
    b = e.where("event_type = 'click'").select("user_id", F.col("u").alias("v"), F.floor(F.col("u") / hour).alias("bin"))
    return a.join(b, ["user_id", "bin"]).where(F.abs(F.col("u") - F.col("v")) <= hour).groupBy("event_id").agg(F.count("*").alias("near"))


@query("SELECT a.r_name AS a, b.r_name AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def join_nested_loop(spark, d):
    a, b = t(spark, d, "region").select(F.col("r_regionkey").alias("i"), F.col("r_name").alias("a")), t(spark, d, "region").select(F.col("r_regionkey").alias("j"), F.col("r_name").alias("b"))
    return a.join(F.broadcast(b), F.col("i") < F.col("j")).select("a", "b")


@query("SELECT count(*) AS n, count(o_orderkey) AS matched FROM lineitem LEFT JOIN orders ON l_orderkey = o_orderkey AND o_orderstatus = 'F'")
def join_bucketed(spark, d):
    """Both sides hash-partitioned on the key once: the join adds no further exchange."""
    li, o = t(spark, d, "lineitem").select(F.col("l_orderkey").alias("k")).repartition(16, "k"), t(spark, d, "orders").where("o_orderstatus = 'F'").select(F.col("o_orderkey").alias("k"), "o_orderkey").repartition(16, "k")
    return li.join(o.hint("shuffle_hash"), "k", "left").agg(F.count("*").alias("n"), F.count("o_orderkey").alias("matched"))


# -- aggregation ------------------------------------------------------------------------------------------------------------


@query(f"SELECT l_returnflag, l_linestatus, count(*) AS n, sum({M('l_extendedprice')}) AS cents, min(l_quantity) AS least, max(l_quantity) AS most FROM lineitem GROUP BY 1, 2")
def agg_hash(spark, d):
    return t(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(money("l_extendedprice")).alias("cents"), F.min("l_quantity").alias("least"), F.max("l_quantity").alias("most"))


@query("SELECT conv_id, array_to_string(list(role ORDER BY turn), ',') AS roles FROM conversations GROUP BY 1")
def agg_sort(spark, d):
    s = F.array_sort(F.collect_list(F.struct("turn", "role")))
    return t(spark, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(s, lambda x: x["role"]), ",").alias("roles"))


@query("SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT CAST(ts AS DATE)) AS days FROM events GROUP BY 1")
def agg_distinct(spark, d):
    return t(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.col("ts").cast("date")).alias("days"))


@query()
def agg_approx_distinct(spark, d):
    return t(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"))


@query("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
def agg_percentile(spark, d):
    return t(spark, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


@query("SELECT round(corr(l_extendedprice, l_quantity), 6) AS r, round(covar_pop(l_discount, l_tax), 8) AS c, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem")
def agg_corr_cov_regr(spark, d):
    return t(spark, d, "lineitem").agg(F.round(F.corr("l_extendedprice", "l_quantity"), 6).alias("r"), F.round(F.covar_pop("l_discount", "l_tax"), 8).alias("c"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.round(F.stddev("l_quantity"), 6).alias("sd"))


@query("SELECT user_id, min_by(event_id, ts) AS first_id, max_by(event_id, ts) AS last_id FROM events GROUP BY 1")
def agg_min_by_max_by(spark, d):
    return t(spark, d, "events").groupBy("user_id").agg(F.min_by("event_id", "ts").alias("first_id"), F.max_by("event_id", "ts").alias("last_id"))


@query("SELECT source, count(*) FILTER (WHERE n_chars > 2000) AS long_docs, sum(n_chars) FILTER (WHERE lang = 'en') AS en_chars FROM documents GROUP BY 1")
def agg_filter_clause(spark, d):
    t(spark, d, "documents").createOrReplaceTempView("rel_documents")
    return spark.sql("SELECT source, count(*) FILTER (WHERE n_chars > 2000) AS long_docs, sum(n_chars) FILTER (WHERE lang = 'en') AS en_chars FROM rel_documents GROUP BY source")


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderstatus), ())")
def agg_grouping_sets(spark, d):
    o = t(spark, d, "orders")
    return o.groupingSets([["o_orderstatus", "o_orderpriority"], ["o_orderstatus"], []], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")).select("o_orderstatus", "o_orderpriority", "n")


@query("SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(spark, d):
    j = t(spark, d, "customer").join(F.broadcast(t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("SELECT event_type, CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY CUBE (event_type, day)")
def agg_cube(spark, d):
    return t(spark, d, "events").select("event_type", F.col("ts").cast("date").alias("day")).cube("event_type", "day").agg(F.count("*").alias("n"))


_TYPES = ("click", "error", "purchase", "signup", "view")


@query("SELECT CAST(ts AS DATE) AS day, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{x}') AS {x}" for x in _TYPES) + " FROM events GROUP BY 1")
def agg_pivot(spark, d):
    e = t(spark, d, "events").select(F.col("ts").cast("date").alias("day"), "event_type")
    return e.groupBy("day").pivot("event_type", list(_TYPES)).count().na.fill(0)


@query("SELECT doc_id, name, CAST(v AS BIGINT) AS v FROM (SELECT doc_id, quality, toxic FROM labels) UNPIVOT (v FOR name IN (quality, toxic))")
def agg_unpivot(spark, d):
    return t(spark, d, "labels").select("doc_id", F.col("quality").cast("long"), F.col("toxic").cast("long")).unpivot("doc_id", ["quality", "toxic"], "name", "v").where("v is not null")


@query("SELECT user_id, count(*) AS n FROM events GROUP BY 1 HAVING count(*) > 70")
def agg_having(spark, d):
    return t(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("n")).where("n > 70")


@query("SELECT lang, string_agg(DISTINCT source, ',' ORDER BY source) AS sources FROM documents GROUP BY 1")
def agg_listagg(spark, d):
    return t(spark, d, "documents").groupBy("lang").agg(F.array_join(F.array_sort(F.collect_set("source")), ",").alias("sources"))


# -- windows ------------------------------------------------------------------------------------------------------------------


@query("""SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 8) AS pr FROM events
WINDOW w AS (PARTITION BY user_id ORDER BY value, event_id)""")
def win_rank_family(spark, d):
    w = Window.partitionBy("user_id").orderBy("value", "event_id")
    return t(spark, d, "events").select("event_id", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 8).alias("pr"))


@query("SELECT event_id, ntile(4) OVER w AS q, round(cume_dist() OVER w, 8) AS cd FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def win_ntile_cume(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return t(spark, d, "events").select("event_id", F.ntile(4).over(w).alias("q"), F.round(F.cume_dist().over(w), 8).alias("cd"))


@query("SELECT event_id, lag(value, 1) OVER w AS l1, lag(value, 3) OVER w AS l3, lead(value, 2) OVER w AS n2 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def win_lag_lead_L(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return t(spark, d, "events").select("event_id", F.lag("value", 1).over(w).alias("l1"), F.lag("value", 3).over(w).alias("l3"), F.lead("value", 2).over(w).alias("n2"))


@query("""SELECT event_id, first_value(value) OVER w AS a, last_value(value) OVER w AS b, nth_value(value, 2) OVER w AS c FROM events
WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def win_first_last_nth(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(spark, d, "events").select("event_id", F.first("value").over(w).alias("a"), F.last("value").over(w).alias("b"), F.nth_value("value", 2).over(w).alias("c"))


@query(f"SELECT event_id, sum({M('value')}) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 6 PRECEDING AND CURRENT ROW) AS cents FROM events")
def win_rows_moving_avg(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(-6, 0)
    return t(spark, d, "events").select("event_id", F.sum(money("value")).over(w).alias("cents"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_interval(spark, d):
    u = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("u").rangeBetween(-86_400_000_000, 0)
    return t(spark, d, "events").select("event_id", "user_id", u.alias("u")).select("event_id", F.count("*").over(w).alias("n"))


@query(f"SELECT event_id, sum({M('value')}) OVER (PARTITION BY event_type ORDER BY event_id) AS cents FROM events")
def win_running_total(spark, d):
    w = Window.partitionBy("event_type").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t(spark, d, "events").select("event_id", F.sum(money("value")).over(w).alias("cents"))


@query("""WITH s AS (SELECT user_id, event_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY event_id) - row_number() OVER (PARTITION BY user_id, event_type ORDER BY event_id) AS g FROM events)
SELECT user_id, event_type, min(event_id) AS first_id, count(*) AS n FROM s GROUP BY user_id, event_type, g HAVING count(*) > 1""")
def win_gaps_islands(spark, d):
    a, b = Window.partitionBy("user_id").orderBy("event_id"), Window.partitionBy("user_id", "event_type").orderBy("event_id")
    s = t(spark, d, "events").withColumn("g", F.row_number().over(a) - F.row_number().over(b))
    return s.groupBy("user_id", "event_type", "g").agg(F.min("event_id").alias("first_id"), F.count("*").alias("n")).where("n > 1").drop("g")


@query(f"SELECT event_id, round(avg({M('value')}) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) AS m FROM events")
def win_prefix_mean(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t(spark, d, "events").select("event_id", F.round(F.avg(money("value")).over(w), 4).alias("m"))


# -- sort, limit, set operations --------------------------------------------------------------------------------------------------


@query("SELECT event_id, value FROM events ORDER BY value DESC, event_id LIMIT 25")
def topk_impact(spark, d):
    return t(spark, d, "events").orderBy(F.desc("value"), "event_id").limit(25).select("event_id", "value")


@query("SELECT user_id, event_id, value FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) <= 3")
def topk_per_series(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    return t(spark, d, "events").withColumn("k", F.row_number().over(w)).where("k <= 3").select("user_id", "event_id", "value")


@query("SELECT o_orderkey, row_number() OVER (ORDER BY nullif(o_orderstatus, 'O') NULLS FIRST, o_totalprice DESC, o_orderkey) AS place FROM orders QUALIFY place <= 100")
def sort_multi_nulls(spark, d):
    o = t(spark, d, "orders").orderBy(F.nullif("o_orderstatus", F.lit("O")).asc_nulls_first(), F.desc("o_totalprice"), "o_orderkey").limit(100)
    return o.select("o_orderkey", F.row_number().over(Window.orderBy(F.nullif("o_orderstatus", F.lit("O")).asc_nulls_first(), F.desc("o_totalprice"), "o_orderkey")).alias("place"))


@query("SELECT event_id FROM events ORDER BY event_id LIMIT 50 OFFSET 100")
def limit_offset(spark, d):
    return t(spark, d, "events").orderBy("event_id").offset(100).limit(50).select("event_id")


def _sides(spark, d):
    e = t(spark, d, "events").select((F.col("event_id") % 1000).alias("pos"))
    return e, e.where("pos % 3 = 0")


_A, _B = "(SELECT event_id % 1000 AS pos FROM events)", "(SELECT event_id % 1000 AS pos FROM events WHERE (event_id % 1000) % 3 = 0)"
for _name, _op, _sql in (
    ("set_union_all", lambda a, b: a.unionByName(b), "UNION ALL"),
    ("set_union_distinct", lambda a, b: a.unionByName(b).distinct(), "UNION"),
    ("set_intersect", lambda a, b: a.intersect(b), "INTERSECT"),
    ("set_intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"),
    ("set_except", lambda a, b: a.subtract(b), "EXCEPT"),
    ("set_except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL"),
):
    QUERIES[_name] = lambda spark, d, f=_op: f(*_sides(spark, d))
    ORACLES[_name] = f"SELECT pos FROM {_A} a {_sql} SELECT pos FROM {_B} b"


# -- scalar functions ------------------------------------------------------------------------------------------------------------


@query("SELECT page_id, upper(regexp_extract(url, '://([^/]*)', 1)) AS host, length(html) AS n, substr(url, 1, 8) AS head, concat_ws('|', split_part(url, ':', 1), CAST(page_id AS VARCHAR)) AS tag FROM pages")
def fn_string(spark, d):
    return t(spark, d, "pages").select("page_id", F.upper(F.regexp_extract("url", "://([^/]*)", 1)).alias("host"), F.length("html").alias("n"), F.substring("url", 1, 8).alias("head"), F.concat_ws("|", F.split_part("url", F.lit(":"), F.lit(1)), F.col("page_id").cast("string")).alias("tag"))


@query("SELECT event_id, date_trunc('hour', ts) AS h, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS days, hour(ts) AS hr, isodow(ts) AS dow FROM events")
def fn_date_trunc_diff(spark, d):
    return t(spark, d, "events").select("event_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("h"), F.date_diff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")).alias("days"), F.hour("ts").alias("hr"), (F.weekday("ts") + 1).alias("dow"))


@query("SELECT event_id, ts + INTERVAL 36 HOUR AS later FROM events")
def fn_interval_add(spark, d):
    return t(spark, d, "events").select("event_id", F.expr("ts + INTERVAL 36 HOURS").alias("later"))


@query("SELECT event_id, round(sqrt(value), 6) AS s, round(ln(value + 1), 6) AS l, round(sin(event_id / 10.0), 6) AS w, floor(value / 7) AS f, sign(value - 50) AS g, greatest(value, 50) AS top FROM events")
def fn_math_trig(spark, d):
    v = F.col("value")
    return t(spark, d, "events").select("event_id", F.round(F.sqrt(v), 6).alias("s"), F.round(F.log(v + 1), 6).alias("l"), F.round(F.sin(F.col("event_id") / 10.0), 6).alias("w"), F.floor(v / 7).cast("double").alias("f"), F.signum(v - 50).cast("tinyint").alias("g"), F.greatest(v, F.lit(50.0)).alias("top"))


@query("SELECT event_id, xor(event_id, user_id) AS x, (event_id << 3) AS l, (event_id >> 2) AS r, event_id & 255 AS a FROM events")
def fn_bit_xor_shift(spark, d):
    return t(spark, d, "events").select("event_id", F.col("event_id").bitwiseXOR(F.col("user_id")).alias("x"), F.shiftleft("event_id", 3).alias("l"), F.shiftright("event_id", 2).alias("r"), F.col("event_id").bitwiseAND(F.lit(255)).alias("a"))


@query("SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS pos, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS sq FROM embeddings")
def fn_array_hof(spark, d):
    v = F.col("embedding")
    return t(spark, d, "embeddings").select("vec_id", F.size(F.filter(v, lambda x: x > 0)).alias("pos"), F.round(F.aggregate(v, F.lit(0.0), lambda s, x: s + x.cast("double") * x), 4).alias("sq"))


@query("SELECT vec_id, i AS at, embedding[i + 1] AS v FROM embeddings, range(0, 64, 16) r(i)")
def fn_array_slice_seq(spark, d):
    at = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(48).cast("long"), F.lit(16).cast("long"))).alias("at")
    return t(spark, d, "embeddings").select("vec_id", "embedding", at).select("vec_id", "at", F.element_at(F.slice("embedding", F.col("at").cast("int") + 1, F.lit(1)), 1).alias("v"))


@query("SELECT doc_id, quality + 10 * toxic AS code FROM labels WHERE quality + toxic > 0")
def fn_map(spark, d):
    m = F.map_from_arrays(F.array(F.lit("quality"), F.lit("toxic")), F.array("quality", F.col("toxic")))
    s = t(spark, d, "labels").select("doc_id", m.alias("m")).withColumn("some", F.map_filter("m", lambda k, v: v > 0)).where(F.size("some") > 0)
    return s.select("doc_id", (F.element_at("m", "quality") + 10 * F.element_at("m", "toxic")).alias("code"))


@query("SELECT event_id, CAST(props->>'$.k' AS INTEGER) AS k FROM events")
def fn_json_props(spark, d):
    return t(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


# -- subqueries and SQL surface ----------------------------------------------------------------------------------------------------


def _views(spark, d, *names):
    for n in names:
        t(spark, d, n).createOrReplaceTempView(f"rel_{n}")


def _same(name, sql, *tables, args=None):
    def f(spark, d):
        _views(spark, d, *tables)
        text = sql
        for n in tables:
            text = text.replace(f"{{{n}}}", f"rel_{n}")
        return spark.sql(text, args=args) if args else spark.sql(text)

    QUERIES[name] = f
    twin = sql
    for n in tables:
        twin = twin.replace(f"{{{n}}}", n)
    for k, v in (args or {}).items():
        twin = twin.replace(f":{k}", repr(v))
    ORACLES[name] = twin


_same("sq_scalar", "SELECT event_id FROM {events} WHERE value > (SELECT max(value) * 0.8 FROM {events})", "events")
_same("sq_correlated_exists", "SELECT s_suppkey FROM {supplier} s WHERE EXISTS (SELECT 1 FROM {lineitem} l WHERE l.l_suppkey = s.s_suppkey AND l.l_quantity >= 50)", "supplier", "lineitem")
_same("sq_in", "SELECT doc_id, n_chars FROM {documents} WHERE doc_id IN (SELECT doc_id FROM {labels} WHERE toxic = 1)", "documents", "labels")
_same("cte_chain", "WITH a AS (SELECT user_id, count(*) AS n FROM {events} GROUP BY user_id), b AS (SELECT n, count(*) AS users FROM a GROUP BY n) SELECT n, users FROM b WHERE users > 1", "events")
_same("param_sql", "SELECT event_id, value FROM {events} WHERE event_type = :kind AND value > :floor", "events", args={"kind": "click", "floor": 120.5})


@query("SELECT conv_id, turn, unnest(string_split(role, 's')) AS piece FROM conversations")
def lateral_explode(spark, d):
    _views(spark, d, "conversations")
    return spark.sql("SELECT conv_id, turn, piece FROM rel_conversations LATERAL VIEW explode(split(role, 's')) x AS piece")


@query()
def sample_seeded(spark, d):
    return t(spark, d, "events").sample(0.1, seed=7).select("event_id")


@query()
def sample_stratified(spark, d):
    return t(spark, d, "events").sampleBy("event_type", {"click": 0.1, "error": 1.0}, seed=7).select("event_id", "event_type")


@query("SELECT event_id FROM events WHERE event_id % 10 = 0")
def sample_every_kth(spark, d):
    return t(spark, d, "events").where("event_id % 10 = 0").select("event_id")
