"""What several operators of this subpackage share: lineage cuts, table access and distributed union-find."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def checkpoint_folder(spark: SparkSession) -> str:
    """The shared folder of checkpoints, from ``spark.checkpoint.dir``; a temporary one in local mode only, where no other machine has to see it."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if not shared and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="checkpoints-"))
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared checkpoint folder and continue from there, so that a lost executor costs no recomputation."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """As ``cut``, in compressed columns: written as Parquet to the shared folder and read again."""
    path = f"{checkpoint_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def beside(df: DataFrame, most: int = 1_000_000) -> DataFrame:
    """``df`` stored, and broadcast to what it is joined with where it has at most ``most`` rows, so that texts stay where they are.

    Without the hint a table from a checkpoint counts as large, and both sides are shuffled before their sizes are known.
    """
    df = stored(df)
    return F.broadcast(df) if df.count() <= most else df


def components(edges: DataFrame, a: str, b: str, max_rounds: int = 60) -> DataFrame:
    """Distributed union-find over an edge list: ``(node, component)`` with the smallest node reachable.

    Alternates two contractions until the edge set is a forest of stars. In each, minima are taken with map-side
    combination and brought back by a join that adaptive execution can split, so a node with a third of all edges
    is never gathered in one task. Roots and isolated nodes have no row: callers coalesce to the node itself.
    Null endpoints and self loops are ignored; an empty input gives an empty result.
    """
    e = cut(
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v"))
        .where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col("u") != F.col("v")))
        .distinct()
    )
    for _ in range(max_rounds):
        if e.isEmpty():
            break
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        before, e = e, cut(small.unionByName(low.select("u", F.col("m").alias("v"))).where("u != v").distinct())
        # stars at last: both edge sets are distinct, so they are the same if none of the new is missing in the old and their sizes agree
        if before.count() == e.count() and e.join(before, ["u", "v"], "left_anti").isEmpty():
            break
    else:
        raise RuntimeError("components did not settle; raise max_rounds")
    return e.select(F.col("u").alias("node"), F.col("v").alias("component"))
