"""Reading tables and writing series."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def write_series(df: DataFrame, path: str, buckets: int = 16, format: str = "parquet", mode: str = "overwrite") -> None:
    """Partitioned by a bucket of the series id, sorted by series and position, so that one series is one run of one file."""
    out = df.withColumn("series_bucket", F.pmod(F.xxhash64("series_id"), F.lit(buckets)).cast("int"))
    out = out.repartition(buckets, "series_bucket").sortWithinPartitions("series_bucket", "series_id", "pos")
    out.write.mode(mode).partitionBy("series_bucket").format(format).save(path)


def read_series(spark: SparkSession, path: str, format: str = "parquet") -> DataFrame:
    return spark.read.format(format).load(path).drop("series_bucket")
