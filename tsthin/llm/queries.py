"""The registered queries of this subpackage: thin wrappers that apply each operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .support import table

#: Rules (verdict, host, path), fixed values.
URL_RULES = [
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
]


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"), words=3, radius=2)


def op2_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .bpe import encode_corpus, read_tokenizer

    tokenizer = read_tokenizer(public_tokenizers.path("byte_bpe_50k.json"))
    coded = encode_corpus(table(spark, sf_dir, "documents"), tokenizer, ids=False, decoded=False)
    return coded.select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontaminate import contaminated

    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), occurrences=True)


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .secret_scan import scan

    found = scan(table(spark, sf_dir, "documents"), owner=F.col("source"))
    return found.drop("findings")


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .line_dedup import dedup_lines

    kept = dedup_lines(table(spark, sf_dir, "documents"), min_chars=1)  # short lines too are compared, not only their exact copies
    return kept.select("doc_id", F.col("_dropped").alias("n_dropped"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op6_embedding_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .embed_join import near_duplicates

    return near_duplicates(table(spark, sf_dir, "embeddings"), least=0.93)


def op7_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .chat import as_log, digest, fold, format_messages

    log = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = r"\### Assistant: </turn> ok"
    own = spark.sql(f"SELECT * FROM VALUES (-7L, 0L, 'user', r'{said}'), (-7L, 1L, 'assistant', r'{said}') AS t(conv_id, turn, role, text)")
    return digest(format_messages(fold(as_log(log.unionByName(own)))))


def op8_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .repeats import remove_repeats

    found = remove_repeats(table(spark, sf_dir, "documents"), length=50)
    return found.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), "kept_sha256")


def op9_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .langid import fit, held_out, predict

    docs = table(spark, sf_dir, "documents")
    model = fit(docs.where(~held_out()))
    return predict(docs, model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .urlfilter import judge

    rules = spark.sql("SELECT * FROM VALUES " + ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in URL_RULES) + " AS t(verdict, host, path)")
    return judge(table(spark, sf_dir, "pages"), rules)


OP10_SQL = r"""
WITH u AS (
  SELECT page_id,
         coalesce(translate(regexp_extract(url, '^[\s\S]*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
         coalesce(regexp_extract(url, '^[\s\S]*?://[^/?#]*([^?#]*)', 1), '') AS path
  FROM pages),
r(verdict, h, p) AS (VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'),
                            ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
m AS (
  SELECT u.*, r.h || r.p AS rule, r.verdict AS v,
         row_number() OVER (PARTITION BY page_id ORDER BY length(r.h || r.p) DESC NULLS LAST, length(r.h) DESC) AS k
  FROM u LEFT JOIN r ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p))
SELECT page_id, host, path, rule, coalesce(v, 'allow') AS verdict FROM m WHERE k = 1
"""

#: Template lengths are those of the markers; one character is added before each backslash and control string.
OP7_SQL = r"""
WITH m AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL VALUES (-7, 0, 'user', '\### Assistant: </turn> ok'), (-7, 1, 'assistant', '\### Assistant: </turn> ok')),
e AS (
  SELECT *, len(regexp_extract_all(text, '\\|###|</turn>')) + len(regexp_extract_all(role, '\\|###|</turn>|\n')) AS marks FROM m)
SELECT conv_id, count(*) AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
       CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
       CAST(sum(4 + length(role) + 2 + length(text) + marks + 9) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""

OP6_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
    AND len([x FOR x IN embedding IF x IS NULL OR NOT isfinite(x)]) = 0
    AND len([x FOR x IN embedding IF x <> 0]) > 0),
l AS (
  SELECT a.vec_id AS a, b.vec_id AS b
  FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
  WHERE list_cosine_similarity(a.e, b.e) >= 0.93),
r(node, seen) AS (
  SELECT vec_id, vec_id FROM embeddings
  UNION
  SELECT l.b, r.seen FROM r JOIN l ON r.node = l.a WHERE r.seen < l.b),
c AS (SELECT node, min(seen) AS component_id FROM r GROUP BY node),
n AS (SELECT a, count(*) AS n_links FROM l GROUP BY a)
SELECT node AS vec_id, coalesce(n_links, 0) AS n_links, component_id, node = component_id AS kept
FROM c LEFT JOIN n ON a = node
"""

OP8_SQL = """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
b AS (  -- blocks of 512 starts, since taking a part of a long text costs its length
  SELECT doc_id, k, substr(h, 2 * k + 1, 1122) AS h
  FROM (SELECT doc_id, h, unnest(range(0, CAST(length(h) / 2 - 49 AS BIGINT), 512)) AS k FROM d WHERE length(h) >= 100)),
p AS (
  SELECT doc_id, k + j AS i, substr(h, 2 * j + 1, 100) AS s
  FROM (SELECT doc_id, h, k, unnest(range(least(512, CAST(length(h) / 2 - 49 AS BIGINT)))) AS j FROM b)),
f AS (SELECT s, min(doc_id) AS first FROM p GROUP BY s HAVING min(doc_id) < max(doc_id)),
g AS (SELECT p.doc_id, p.i, p.i - lag(p.i) OVER (PARTITION BY p.doc_id ORDER BY p.i) AS step FROM p JOIN f USING (s) WHERE p.doc_id > f.first),
k AS (SELECT doc_id, i, sum(CASE WHEN step IS NULL OR step > 50 THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM g),
r AS (SELECT doc_id, min(i) AS a, max(i) + 50 AS b FROM k GROUP BY doc_id, run),
q AS (SELECT *, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS before FROM r),
t AS (
  SELECT doc_id, count(*) AS n_spans, sum(b - a) AS n_removed, max(b) AS last,
         string_agg(substr(h, 2 * before + 1, 2 * (a - before)), '' ORDER BY a) AS kept
  FROM q JOIN d USING (doc_id) GROUP BY doc_id)
SELECT doc_id, CAST(length(h) / 2 AS BIGINT) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed,
       coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept, '') || substr(h, 2 * coalesce(last, 0) + 1))) AS kept_sha256
FROM d LEFT JOIN t USING (doc_id)
"""

#: Kinds as the contract words them: kind, rank, pattern, group with the least length, condition on the value ``v``.
_OP4_KINDS = [
    ("assign", 0, r"""(?i:password|passwd|secret|token|api_?key)["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)""", 1, "length(v) >= 12"),
    ("access", 1, "AKIA[A-Z0-9]+", 0, "length(v) >= 18"),
    ("hex", 2, "[0-9a-f]+", 0, "length(v) >= 16"),
    ("mixed", 3, "[A-Za-z0-9+/_-]{20,}", 0, "regexp_matches(v, '[0-9]') AND regexp_matches(v, '[a-z]') AND regexp_matches(v, '[A-Z]')"),
]
_OP4_FOUND = " UNION ALL ".join(
    f"""SELECT doc_id, owner, '{kind}' AS kind, {rank} AS rank, v, b AS start, b + length(m) AS stop
  FROM (SELECT doc_id, owner, m, v, CAST(sum(length(g) + length(m)) OVER (PARTITION BY doc_id ORDER BY i) AS BIGINT) - length(m) AS b
        FROM (SELECT doc_id, owner, unnest(range(len(ms))) AS i, unnest(ms) AS m, unnest(vs) AS v, unnest(gs[1:len(ms)]) AS g
              FROM (SELECT doc_id, owner, regexp_extract_all(text, '{pattern}') AS ms, regexp_extract_all(text, '{pattern}', {group}) AS vs,
                           string_split_regex(text, '{pattern}') AS gs FROM t)))
  WHERE {holds}"""
    for kind, rank, pattern, group, holds in _OP4_KINDS
)
OP4_SQL = f"""
WITH t AS (SELECT doc_id, coalesce(source, '') AS owner, coalesce(text, '') AS text FROM documents),
x AS ({_OP4_FOUND}),
o AS (SELECT v, count(DISTINCT owner) AS owners FROM x GROUP BY v),
j AS (SELECT x.*, owners < 2 AS live, kind || ':' || start || ':' || stop AS said FROM x JOIN o USING (v)),
y AS (
  SELECT * FROM j WHERE rank < 3 OR (live AND NOT EXISTS (
    SELECT 1 FROM x b WHERE b.doc_id = j.doc_id AND b.rank < 3 AND b.start < j.stop AND j.start < b.stop)))
SELECT t.doc_id, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex,
       sha256(coalesce(string_agg(said, ',' ORDER BY start, rank) FILTER (rank < 3), '')) AS base_sha256,
       coalesce(string_agg(said, ',' ORDER BY start, rank), '') AS spans, count(*) FILTER (live) AS live, count(*) FILTER (NOT live) AS copied
FROM t LEFT JOIN y ON t.doc_id = y.doc_id GROUP BY t.doc_id
"""

QUERIES = {"op1_simhash": op1_simhash, "op2_bpe": op2_bpe, "op3_decontaminate": op3_decontaminate, "op4_secret_scan": op4_secret_scan, "op5_line_dedup": op5_line_dedup, "op6_embedding_join": op6_embedding_join, "op7_chat_format": op7_chat_format, "op8_repeats": op8_repeats, "op9_language": op9_language, "op10_url_filter": op10_url_filter}
ORACLES = {"op4_secret_scan": OP4_SQL, "op6_embedding_join": OP6_SQL, "op7_chat_format": OP7_SQL, "op8_repeats": OP8_SQL, "op10_url_filter": OP10_SQL}
