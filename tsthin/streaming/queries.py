"""Streaming queries: events replayed as a file stream, run to the end, compared with the batch form of the same question."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..kernel.greedy import Rules
from ..plans.relational import _scratch
from ..plans.series_queries import USERS
from ..sources import fixtures as fx
from ..sources.tables import load_table as t
from .online import thin_chunks, thin_online

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def replay(spark: SparkSession, df: DataFrame, files: int = 4, order: str | None = None) -> DataFrame:
    """``df`` as a stream: written to the shared folder in so many files and read file by file."""
    path = _scratch(spark)
    if order is None:
        df.repartition(files).write.parquet(path)
    else:  # one write after the other, so that files are read in order
        at = F.unix_micros(order) if df.schema[order].dataType.typeName() == "timestamp" else F.col(order)
        cuts = df.select(F.percentile_approx(at, [k / files for k in range(1, files)])).first()[0]
        for lo, hi in zip([None, *cuts], [*cuts, None]):
            part = df if lo is None else df.where(at > lo)
            (part if hi is None else part.where(at <= hi)).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def events(spark, d) -> DataFrame:
    e = t(spark, d, "events")
    return e.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")


def finish(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream over all that is there; what it emitted, from the shared folder (append) or a memory table."""
    spark = stream.sparkSession
    if mode == "append":
        out = _scratch(spark)
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", _scratch(spark)).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    name = f"stream_{uuid.uuid4().hex}"
    stream.writeStream.format("memory").queryName(name).option("checkpointLocation", _scratch(spark)).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def plain(*cols):
    return [F.col(c).cast("timestamp_ntz").alias(c) if c in ("start", "ts") else F.col(c) for c in cols]


@query("SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def st_tumbling(spark, d):
    s = replay(spark, events(spark, d)).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return finish(s.select(F.col("w.start").alias("start"), "event_type", "n"), "complete").select(*plain("start", "event_type", "n"))


@query("""WITH w AS (SELECT unnest(range(-1, 60)) AS k), b AS (SELECT TIMESTAMP '2024-01-01' + k * INTERVAL 12 HOUR AS start FROM w)
SELECT start, count(*) AS n FROM b JOIN events ON ts >= start AND ts < start + INTERVAL 1 DAY GROUP BY 1""")
def st_sliding(spark, d):
    s = replay(spark, events(spark, d)).groupBy(F.window("ts", "1 day", "12 hours").alias("w")).agg(F.count("*").alias("n"))
    return finish(s.select(F.col("w.start").alias("start"), "n"), "complete").select(*plain("start", "n"))


@query("""WITH a AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w >= INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
b AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM a) SELECT user_id, min(ts) AS start, count(*) AS n FROM b GROUP BY user_id, g""")
def st_session(spark, d):
    s = replay(spark, events(spark, d)).groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return finish(s.select("user_id", F.col("w.start").alias("start"), "n"), "complete").select(*plain("user_id", "start", "n"))


@query("SELECT date_trunc('day', ts) AS start, count(*) AS n FROM events WHERE ts < (SELECT date_trunc('day', max(ts) - INTERVAL 2 DAY) FROM events) GROUP BY 1")
def st_watermark_late(spark, d):
    """Windows that the watermark has closed, appended once; files come in order of time and reach back one day."""
    s = replay(spark, events(spark, d), 4, "ts").withWatermark("ts", "2 days").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return finish(s.select(F.col("w.start").alias("start"), "n")).select(*plain("start", "n"))


@query("SELECT DISTINCT event_id FROM events")
def st_dedup(spark, d):
    e = events(spark, d)
    s = replay(spark, e.unionByName(e), 4, "ts").withWatermark("ts", "2 days").dropDuplicatesWithinWatermark(["event_id"])
    return finish(s.select("event_id"))


@query("SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
def st_static_join(spark, d):
    c = t(spark, d, "customer").select("c_custkey", "c_mktsegment")
    return finish(replay(spark, events(spark, d)).join(F.broadcast(c), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


@query("""SELECT a.event_id AS bought, b.event_id AS clicked FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type = 'click'
AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts""")
def st_stream_stream_interval(spark, d):
    e = events(spark, d)
    a = replay(spark, e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("bought"), F.col("ts").alias("at")), 2, "at").withWatermark("at", "40 days")
    b = replay(spark, e.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("event_id").alias("clicked"), F.col("ts").alias("ct")), 2, "ct").withWatermark("ct", "40 days")
    j = a.join(b, F.expr("user_id = u AND ct BETWEEN at - INTERVAL 1 HOUR AND at"))
    return finish(j.select("bought", "clicked"))


ONLINE = Rules(lags=(1, 2, 3), eps=0.05, hops="all")


@query(f"""SELECT series_id, chunk, true AS same FROM (SELECT series_id, pos // 20 AS chunk, max(pos // 20) OVER (PARTITION BY series_id) AS last FROM {USERS}) WHERE chunk < last GROUP BY 1, 2""")
def st_stateful_thin(spark, d):
    """Online thinning of closed chunks equals thinning the chunks of the table."""
    s = fx.user_seq(spark, d)
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        live = finish(thin_online(replay(spark, s, 3, "pos"), ONLINE, 20))
    finally:
        spark.conf.set(key, before)
    same = lambda x, n: x.groupBy("series_id", "chunk").agg(F.array_sort(F.collect_list("pos")).alias(n))
    j = same(thin_chunks(s, ONLINE, 20), "a").join(same(live, "b"), ["series_id", "chunk"], "left")
    return j.select("series_id", "chunk", F.coalesce(F.col("a") == F.col("b"), F.lit(False)).alias("same"))


@query("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def st_foreach_batch(spark, d):
    out = _scratch(spark)

    def put(batch: DataFrame, k: int) -> None:
        batch.groupBy("event_type").agg(F.count("*").alias("n")).write.mode("overwrite").parquet(f"{out}/batch={k}")

    replay(spark, events(spark, d)).writeStream.foreachBatch(put).option("checkpointLocation", _scratch(spark)).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).groupBy("event_type").agg(F.sum("n").alias("n"))
