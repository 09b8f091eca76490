"""Corpus pipeline: language ID, line dedup, SimHash near-dedup, benchmark decontamination, BPE encoding and decoding.

Each stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame that is written as Parquet and read again as the
next one's ``docs``. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tsthin.llm import bpe, decontaminate, langid, line_dedup, simhash
from tsthin.llm.support import beside, checkpoint_folder, table

#: Of a language prediction; texts without letters and those below go. Two winning votes give 0.25 at least. Of
#: held-out documents of check_s 99.5 % score above 0.6; random letters and base64 mostly score 0.3 to 0.5.
LEAST_SCORE = 0.6


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a recognised language go."""
    told = langid.predict(docs, langid.fit(docs), keep=[c for c in docs.columns if c != "doc_id"])
    return told.where((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SCORE)).select(docs.columns)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every line stays once, in the first document that holds it; documents stay, with what is left of them.

    Lines under 20 characters go where they are exact repeats, longer ones where they are similar too; blank lines stay.
    """
    left = line_dedup.dedup_lines(docs, short_copies=True).select(docs.columns)
    return left.withColumn("n_chars", F.length("text").cast("bigint")) if "n_chars" in docs.columns else left


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays, the one with the smallest id (all rows of that id).

    Groups are of five-word shingles of Jaccard similarity 0.8 or more, verified exactly: pairs of near fingerprints,
    and pairs whose fingerprints are too far apart for a search.
    """
    found = simhash.jaccard_components(docs, "doc_id", "text", words=5, least=0.8)
    return docs.join(beside(found.where("node != component").select("node")), docs["doc_id"] == F.col("node"), "left_anti").select(docs.columns)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    leaks = decontaminate.contaminated(docs, table(spark, sf_dir, "benchmark"), occurrences=True).select("doc_id").distinct()
    return docs.join(leaks, "doc_id", "left_anti").select(docs.columns)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """``(doc_id, n_tokens, ids, ids_sha256, decoded_sha256)``; the last digests the words' decoded bytes, not the emitted ids."""
    import public_tokenizers

    tokenizer = bpe.read_tokenizer(public_tokenizers.path("byte_bpe_50k.json"))
    return bpe.encode_corpus(docs, tokenizer, decoded=False).drop("decoded")


STAGES = [
    ("language ID", language),
    ("line dedup", lines),
    ("SimHash near-dedup", near_copies),
    ("benchmark decontamination", decontaminated),
    ("BPE encoding and decoding", tokens),
]

#: SQL cannot express the trained language model, fingerprint search and tokenizer; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages on ``documents``, each result written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    folder = f"{checkpoint_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
    return docs
