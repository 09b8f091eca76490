"""URL filters: host-suffix and path-prefix expressions, joined on short hash prefixes and confirmed by full digests."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    """Between the first ``://`` and the next ``/``, ``?``, ``#`` or the end, A-Z lower-cased; empty without ``://`` or for null."""
    return F.coalesce(F.translate(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    """After the host up to ``?``, ``#`` or the end; empty without ``://`` or for null."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def _digest(host: Column, path: Column) -> Column:
    return F.sha2(F.concat(host, F.lit("\n"), path), 256)


def _short(digest: Column, hex_digits: int) -> Column:
    return F.conv(F.substring(digest, 1, hex_digits), 16, 10).cast("long")


def judge(
    pages: DataFrame,
    rules: DataFrame,
    id_col: str = "page_id",
    url_col: str = "url",
    default: str = "allow",
    hex_digits: int = 8,
) -> DataFrame:
    """``(id_col, host, path, rule, verdict)``, one row per input row.

    ``rules``: ``(verdict, host, path)``. A rule fits its host and all subdomains if the URL's path starts with the
    rule's path; the longest host and path together win, then the longer host, then block before allow. ``rule`` is
    host and path of the winner, null where none fits; ``verdict`` is then ``default``. URLs that are null or lack
    ``://`` have empty host and path and meet no rule. Repeated ids and rows stay as they are; an empty rule set
    gives everyone the default; null or repeated rules are ignored.

    Each distinct (host, path) is judged once, so a host or a URL with a third of all rows costs one judgement. Its
    expressions (host suffixes times prefixes of the lengths that rules have) meet the rules in an equi-join on the
    first digits of their digests; full digests and then the strings decide.
    """
    urls = pages.select(F.col(id_col), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    r = rules.select(
        F.col("verdict").alias("r_verdict"), F.translate("host", UPPER, LOWER).alias("r_host"), F.col("path").alias("r_path")
    ).where("r_verdict is not null and r_host is not null and r_path is not null")
    r = r.groupBy("r_host", "r_path").agg(F.max("r_verdict").alias("r_verdict"))
    r = r.withColumn("r_digest", _digest(F.col("r_host"), F.col("r_path"))).withColumn("short", _short(F.col("r_digest"), hex_digits))
    lengths = r.agg(F.array_sort(F.collect_set(F.length("r_path"))).alias("lengths"))

    distinct = urls.select("host", "path").distinct()
    labels = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    expressions = (
        distinct.crossJoin(F.broadcast(lengths))  # one row: the path lengths of the rules
        .withColumn("suffix", F.explode(suffixes))
        .withColumn("n", F.explode("lengths"))
        .where(F.col("n") <= F.length("path"))
        .withColumn("prefix", F.expr("substring(path, 1, n)"))
        .withColumn("digest", _digest(F.col("suffix"), F.col("prefix")))
        .withColumn("short", _short(F.col("digest"), hex_digits))
    )
    hits = expressions.join(r, "short").where("digest = r_digest and suffix = r_host and prefix = r_path")
    rank = F.struct(F.length("r_host") + F.length("r_path"), F.length("r_host"), "r_verdict")
    won = hits.groupBy("host", "path").agg(F.max_by(F.struct("r_host", "r_path", "r_verdict"), rank).alias("won"))
    return urls.join(won, ["host", "path"], "left").select(
        id_col,
        "host",
        "path",
        F.concat("won.r_host", "won.r_path").alias("rule"),
        F.coalesce("won.r_verdict", F.lit(default)).alias("verdict"),
    )
