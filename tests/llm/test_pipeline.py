"""The pipeline's stages: contracts, effects, planted cases."""

from __future__ import annotations

import base64

import numpy as np
from conftest import MIDDLE

import corpus_pipeline
from tsthin.llm import bpe, simhash
from tsthin.llm.support import table


def test_stages(spark, tmp_path):
    docs = table(spark, MIDDLE, "documents")
    columns, before = docs.columns, docs
    seen = {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, MIDDLE).write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
        if k < len(corpus_pipeline.STAGES) - 1:
            assert docs.columns == columns, name
        seen[name] = docs
        assert docs.join(before.select("doc_id"), "doc_id", "left_anti").count() == 0
        before = docs
    assert list(seen) == ["language ID", "line dedup", "SimHash near-dedup", "benchmark decontamination", "BPE encoding and decoding"]
    assert seen["language ID"].count() >= 0.99 * 1000 and seen["line dedup"].count() == seen["language ID"].count()
    near, lines = seen["SimHash near-dedup"], seen["line dedup"]
    groups = simhash.near_duplicates(lines, words=5, radius=4)
    assert near.count() == groups.select("component_id").distinct().count()
    last, kept = seen["BPE encoding and decoding"], seen["benchmark decontamination"]
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for r in last.join(kept, "doc_id").limit(200).collect():
        assert list(r["ids"]) == t.encode(r["text"] or "", add_special_tokens=False).ids and len(r["ids"]) == r["n_tokens"]
    assert bpe.decode_documents(last, bpe.read_tokenizer(public_tokenizers.path("byte_bpe_50k.json"))).join(kept, "doc_id").where("decoded != text").count() == 0


def test_clean_documents_stay_and_planted_go(spark):
    clean = "\n".join(f"This is line number {k} of a clean english document about the weather and the garden in week {k * 7}" for k in range(4))
    rows = [(1, clean, "en", "a", 1), (2, "%%% 123 !!!", "en", "a", 1), (3, None, "en", "a", 1), (4, clean, "en", "b", 1)]
    docs = spark.createDataFrame(rows, table(spark, MIDDLE, "documents").schema)
    train = table(spark, MIDDLE, "documents").limit(300)
    told = corpus_pipeline.language(spark, train.unionByName(docs.withColumn("doc_id", docs["doc_id"] + 10**9)), MIDDLE)
    assert {r["doc_id"] - 10**9 for r in told.where("doc_id > 1000000").collect()} == {1, 4}
    left = {r["doc_id"]: r["text"] for r in corpus_pipeline.lines(spark, docs, MIDDLE).collect()}
    assert left[1] == clean or left[1].startswith("This is line number 0")
    assert left[4] == "" and left[3] is None
    stay = {r["doc_id"] for r in corpus_pipeline.near_copies(spark, docs, MIDDLE).collect()}
    assert 1 in stay and 4 not in stay


def test_near_copies_against_brute_force(spark):
    rng = np.random.default_rng(4)
    texts = []
    for n in [3, 40, 100, 300, 800] * 24:
        w = [f"w{x}" for x in rng.integers(0, 5000, n)]
        texts.append(w)
        for changed in rng.uniform(0, 0.06, 2):
            v = list(w)
            for _ in range(int(changed * n)):
                v[int(rng.integers(n))] = f"x{rng.integers(5000)}"
            texts.append(v)
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in texts]
    at = list(range(len(texts)))
    for b in at:
        for a in range(b):
            if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                at = [at[a] if x == at[b] else x for x in at] if at[a] < at[b] else [at[b] if x == at[a] else x for x in at]
    rows = [(i, " ".join(w)) for i, w in enumerate(texts)] + [(1000, ""), (1001, None), (None, "w1"), (None, "w1")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    stay = [r["doc_id"] for r in corpus_pipeline.near_copies(spark, df, MIDDLE).collect()]
    want = {i for i, x in enumerate(at) if x == i} | {1000, None}
    assert len(stay) == len(want) + 1 and len(want) < 0.8 * len(rows) and len(set(stay) ^ want) <= 1


def test_gibberish_and_languages_not_learnt_go(spark):
    rng = np.random.default_rng(6)
    docs = table(spark, MIDDLE, "documents")
    odd = ["".join(rng.choice(list("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ"), 2000)) for _ in range(20)]
    odd += [base64.b64encode(rng.bytes(1500)).decode() for _ in range(20)]
    odd += ["Вчера вечером мы пошли в лес собирать грибы, но начался дождь.", "Tegnap este elmentünk az erdőbe gombát szedni, de eleredt az eső.", "昨天晚上我们去森林里采蘑菇,但是下雨了,我们不得不赶快回家。"]
    planted = spark.createDataFrame([(10**9 + i, t, None, "a", len(t)) for i, t in enumerate(odd)], docs.schema)
    told = corpus_pipeline.language(spark, docs.unionByName(planted), MIDDLE)
    assert told.where("doc_id >= 1000000000").count() == 0
    assert told.count() >= 0.995 * docs.where("text rlike '[A-Za-z]'").count()


def test_near_copies_are_searched_by_fingerprints(spark, monkeypatch):
    words = [f"w{k}" for k in range(400)]
    texts = [" ".join(words), " ".join(words), " ".join([*words, "end"]), " ".join(reversed(words)), "", None]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found, plain = [], simhash.fingerprint_pairs

    def seen(signed, radius):
        pairs = plain(signed, radius)
        found.append((radius, {(r["a"], r["b"]) for r in pairs.collect()}, {r["node"]: r["fp"] % 2**64 for r in signed.collect()}))
        return pairs

    monkeypatch.setattr(simhash, "fingerprint_pairs", seen)
    assert {r["doc_id"] for r in corpus_pipeline.near_copies(spark, df, MIDDLE).collect()} == {0, 3, 4}
    ((radius, pairs, marks),) = found
    assert marks == {k: simhash.fingerprint(t, 5) for k, t in enumerate(texts)}
    near = {(b, a) for a in range(6) for b in range(a + 1, 6) if (marks[a] ^ marks[b]).bit_count() <= radius}
    assert pairs <= near and {(1, 0), (5, 4), (2, 0)} <= pairs


def test_near_copies_leave_texts_where_they_are(spark):
    from test_near_duplicates import shuffled

    rng = np.random.default_rng(9)
    texts = [" ".join(f"w{x}" for x in rng.integers(0, 10**6, 300)) for _ in range(2000)]
    texts += [f"{x} end" for x in texts[:100]]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(8).localCheckpoint()
    before = shuffled(spark)
    assert corpus_pipeline.near_copies(spark, docs, MIDDLE).select("doc_id", "text").agg({"text": "max", "doc_id": "count"}).first()[1] == 2000
    assert shuffled(spark) - before < 0.5 * sum(map(len, texts))
