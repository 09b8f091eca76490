"""Secret scans with corpus-wide ownership frequency, in DataFrame functions only.

Patterns give candidate spans. Candidates' digests are counted over distinct repositories and owners: a value that
several owners hold is a copied example; one that a single owner holds looks live. Besides the base kinds there is a
broad one, ``mixed``: long runs that mix digits, lower and upper case. It gives a span only where ownership says live
and no base span overlaps.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .support import cut

#: Kind, pattern, group that must have the least length, least length.
BASE = [
    ("assign", r"(?i:password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 1, 12),
    ("access", r"AKIA[A-Z0-9]+", 0, 18),
    ("hex", r"[0-9a-f]+", 0, 16),
]
#: Cheap tests that a text must pass to hold a match of the kind at all.
HINTS = {"assign": r"(?i)password|passwd|secret|token|api_?key", "access": r"AKIA[A-Z0-9]{14}", "hex": r"[0-9a-f]{16}", "mixed": r"[A-Za-z0-9+/_-]{20}"}
#: Runs of a kind whose least length is that of the whole match may be asked for at that length at once: runs are maximal.
WHOLE = {"access": r"AKIA[A-Z0-9]{14,}", "hex": r"[0-9a-f]{16,}"}
MIXED = r"[A-Za-z0-9+/_-]{20,}"
SPAN = "array<struct<kind:string,rank:int,start:int,end:int,value:string>>"


def _matches(text: Column, kind: str, rank: int, pattern: str, group: int, least: int) -> Column:
    """Spans of the leftmost non-overlapping matches. Starts are sums of the lengths between and of the matches."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    between = F.split(text, pattern, -1)
    values = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else found
    lengths = F.transform(F.arrays_zip(found.alias("m"), F.slice(between, 1, F.size(found)).alias("b")), lambda x: F.struct(F.length(x["b"]).alias("b"), F.length(x["m"]).alias("m")))
    walked = F.aggregate(
        lengths,
        F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int>>").alias("spans")),
        lambda s, x: F.struct(
            (s["at"] + x["b"] + x["m"]).alias("at"),
            F.concat(s["spans"], F.array(F.struct((s["at"] + x["b"]).alias("start"), (s["at"] + x["b"] + x["m"]).alias("end")))).alias("spans"),
        ),
    )["spans"]
    spans = F.transform(
        F.arrays_zip(walked.alias("s"), values.alias("v")),
        lambda x: F.struct(F.lit(kind).alias("kind"), F.lit(rank).alias("rank"), x["s"]["start"].alias("start"), x["s"]["end"].alias("end"), x["v"].alias("value")),
    )
    return F.filter(spans, lambda x: F.length(x["value"]) >= least)


def _guarded(text: Column, kind: str, spans: Column) -> Column:
    return F.when(text.rlike(HINTS[kind]), spans).otherwise(F.array().cast(SPAN))


def candidates(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """All columns of ``docs`` and ``_base``, ``_broad``: candidate spans (code points, end exclusive) of the whole text."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    base = [_guarded(text, kind, _matches(text, kind, rank, WHOLE.get(kind, pattern), group, least)) for rank, (kind, pattern, group, least) in enumerate(BASE)]
    mixed = F.filter(
        _matches(text, "mixed", len(BASE), MIXED, 0, 20),
        lambda x: x["value"].rlike("[0-9]") & x["value"].rlike("[a-z]") & x["value"].rlike("[A-Z]"),
    )
    return docs.select("*", F.concat(*base).alias("_base"), _guarded(text, "mixed", mixed).alias("_broad"))


def _written(spans: Column) -> Column:
    ordered = F.array_sort(spans, lambda a, b: F.when(a["start"] != b["start"], a["start"] - b["start"]).otherwise(a["rank"] - b["rank"]))
    return F.array_join(F.transform(ordered, lambda x: F.concat_ws(":", x["kind"], x["start"], x["end"])), ",")


def _count(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda x: x["kind"] == kind)).cast("long")


def scan(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    owner: Column | None = None,
    repository: Column | None = None,
    copied_owners: int = 2,
) -> DataFrame:
    """One row per input row: ``id_col``, ``n_<kind>``, ``base_sha256``, ``spans``, ``live``, ``copied``, ``findings``.

    ``findings``: array of (kind, start, end, value digest, repositories, owners, live). A value is copied if at least
    ``copied_owners`` distinct owners hold it, else live. Null text is empty; a null owner or repository counts as one
    owner or repository. Repeated rows and ids are scanned one by one. An empty table gives an empty table. Other
    columns are ignored. Counting is over (value digest, owner, repository) with map-side combination, so a value that
    a third of all rows hold is three aggregations of its counts, never a gathered list.
    """
    owner = F.lit(None).cast("string") if owner is None else owner
    repository = F.col(id_col) if repository is None else repository
    keyed = docs.select(
        F.col(id_col), F.coalesce(owner.cast("string"), F.lit("")).alias("_owner"), F.coalesce(repository.cast("string"), F.lit("")).alias("_repo"), F.col(text_col).alias("_text")
    )
    found = candidates(keyed, "_text").select(id_col, "_owner", "_repo", "_base", "_broad")
    found = cut(found.withColumn("_row", F.monotonically_increasing_id()))  # names a row for the way back; fixed by the checkpoint
    single = found.select("_row", "_owner", "_repo", F.explode(F.concat("_base", "_broad")).alias("x")).withColumn("digest", F.sha2("x.value", 256))
    by_repo = single.groupBy("digest", "_owner", "_repo").agg(F.lit(1).alias("one"))
    by_owner = by_repo.groupBy("digest", "_owner").agg(F.count("*").alias("repos"))
    owned = by_owner.groupBy("digest").agg(F.sum("repos").alias("repositories"), F.count("*").alias("owners"))
    judged = single.join(owned, "digest").withColumn("live", F.col("owners") < copied_owners)
    listed = judged.groupBy("_row").agg(
        F.collect_list(F.struct("x.start", "x.rank", "x.kind", "x.end", "digest", "repositories", "owners", "live")).alias("all")
    )
    rows = found.select("_row", id_col, "_base").join(listed, "_row", "left")
    base = F.col("_base")
    everything = F.coalesce(F.array_sort("all"), F.array().cast("array<struct<start:int,rank:int,kind:string,end:int,digest:string,repositories:bigint,owners:bigint,live:boolean>>"))
    added = lambda x: (x["rank"] == len(BASE)) & x["live"] & ~F.exists(base, lambda y: (y["start"] < x["end"]) & (x["start"] < y["end"]))
    findings = F.filter(everything, lambda x: (x["rank"] < len(BASE)) | added(x))
    return rows.select(
        id_col,
        *[_count(base, kind).alias(f"n_{kind}") for kind, *_ in BASE],
        F.sha2(_written(base), 256).alias("base_sha256"),
        findings.alias("findings"),
    ).select(
        id_col,
        *[f"n_{kind}" for kind, *_ in BASE],
        "base_sha256",
        _written(F.col("findings")).alias("spans"),
        F.size(F.filter("findings", lambda x: x["live"])).cast("long").alias("live"),
        F.size(F.filter("findings", lambda x: ~x["live"])).cast("long").alias("copied"),
        "findings",
    )
