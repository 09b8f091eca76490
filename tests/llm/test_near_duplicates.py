"""Near-duplicate operators against brute force, edges included."""

from __future__ import annotations

import hashlib

import numpy as np
from conftest import MIDDLE, SMALL

from tsthin.llm import embed_join, line_dedup, queries, repeats, simhash
from tsthin.llm.support import components, table


class Union:
    def __init__(self, nodes):
        self.up = {n: n for n in nodes}

    def find(self, x):
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, a, b):
        a, b = self.find(a), self.find(b)
        self.up[max(a, b)] = min(a, b)


def test_components(spark):
    rng = np.random.default_rng(0)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))] + [(i, i + 1) for i in range(400, 450)] + [(500, 500)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "a long, b long"), "a", "b").collect()}
    u = Union({x for e in edges for x in e})
    for a, b in edges:
        u.join(a, b)
    assert all(got.get(n, n) == u.find(n) for n in u.up)
    assert components(spark.createDataFrame([], "a long, b long"), "a", "b").count() == 0


def brute_simhash(fps: dict, radius: int):
    u, rep = Union(fps), {}
    for i in sorted(fps):
        if fps[i] in rep:
            u.join(rep[fps[i]], i)
        rep.setdefault(fps[i], i)
    keys = list(rep)
    v = np.array(keys, dtype=np.uint64)
    for k in range(len(v)):
        for j in np.nonzero(np.bitwise_count(v[k + 1 :] ^ v[k]) <= radius)[0]:
            u.join(rep[keys[k]], rep[keys[k + 1 + j]])
    return {i: u.find(i) for i in fps}


def test_simhash_query(spark):
    got = {r["doc_id"]: r for r in queries.op1_simhash(spark, MIDDLE).collect()}
    texts = {r["doc_id"]: r["text"] for r in table(spark, MIDDLE, "documents").collect()}
    assert len(got) == len(texts)
    fps = {i: simhash.fingerprint(t) for i, t in texts.items()}
    assert all(got[i]["fingerprint"] == f"{fps[i]:016x}" for i in fps)
    want = brute_simhash(fps, 2)
    assert all(got[i]["component_id"] == want[i] for i in fps)


def test_simhash_edges_and_dense_way(spark):
    rng = np.random.default_rng(1)
    words = [f"w{i}" for i in range(50)]
    texts = {i: " ".join(rng.choice(words, 200)) for i in range(5)}
    for k in range(120):  # a cloud of near copies
        w = texts[0].split()
        w[int(rng.integers(200))] = "changed"
        texts[10 + k] = " ".join(w)
    texts |= {200: None, 201: "", 202: " \t\n ", 203: "one", 204: "One", 205: "A b", 206: "É b c", 207: "é b c"}
    df = spark.createDataFrame([(i, t, 1, "x") for i, t in texts.items()], "doc_id long, text string, fp int, component_id string")
    want = brute_simhash({i: simhash.fingerprint(t) for i, t in texts.items()}, 2)
    assert want[201] == 200 and want[204] == 203 and want[207] != want[206]
    for dense in (0, 4, 512):
        got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(df, dense=dense).collect()}
        assert got == want
    twice = df.unionByName(df.limit(3))
    assert simhash.near_duplicates(twice).count() == len(texts) + 3
    assert simhash.near_duplicates(df.limit(0)).count() == 0
    for radius in (1, 4):
        assert {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(df, radius=radius, dense=8).collect()} == brute_simhash({i: simhash.fingerprint(t) for i, t in texts.items()}, radius)


def test_thresholds_keep_the_pigeonhole(spark):
    fps = spark.createDataFrame([(int(x),) for x in np.random.default_rng(0).integers(-(2**62), 2**62, 3000)], "fp long")
    for radius in (1, 2, 3, 6):
        used = simhash.plan(fps, radius)
        parts = [b for bits, _ in used for b in bits]
        assert len(parts) == len(set(parts)) and all(t >= 0 for _, t in used)
        assert sum(t + 1 for _, t in used) == radius + 1
    cost, ts = simhash.allocate([{-1: 0, 0: 10, 1: 20}, {-1: 0, 0: 1, 1: 2}, {-1: 0, 0: 5, 1: 50}], 0)
    assert sum(ts) == 0 and cost == min(10 + 1 + 5, 2 + 5, 2 + 10)


def test_lines(spark):
    base = "the quick brown fox jumps over the lazy dog near the river bank while the sun goes down slowly behind hills"
    rows = [
        (1, f"{base}\nshort\n{base}", "a"), (2, f"{base.upper()}\nshort\nanother line that is long enough to count here", "b"), (3, f"{base}s", "c"),
        (4, None, "d"), (5, "", "e"), (6, "\n\n", "f"), (None, base, "g"), (7, "漢字" * 40, "h"), (8, "漢字" * 40, "i"),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string, at string")
    got = {r["doc_id"]: r for r in line_dedup.dedup_lines(df).collect()}
    assert got[1]["text"] == f"{base}\nshort" and got[2]["text"] == "short\nanother line that is long enough to count here"
    assert got[3]["text"] == "" and got[4]["text"] is None and got[5]["text"] == "" and got[6]["text"] == "\n\n" and got[None]["text"] == base
    assert got[7]["_dropped"] == 0 and got[8]["text"] == "" and got[2]["at"] == "b"
    assert line_dedup.dedup_lines(df.limit(0)).count() == 0


def test_lines_against_all_pairs(spark):
    p = table(spark, SMALL, "documents").select("doc_id", "text")
    first: dict = {}
    rows = sorted((r["doc_id"], r["text"] or "") for r in p.collect())
    for i, t in rows:
        for k, line in enumerate(t.split("\n")):
            n = line.strip(" ").lower()
            if len(n) >= 20:
                first.setdefault(n, (i, k))
    lines = list(first)
    sets = [frozenset(x[a : a + 5] for a in range(max(1, len(x) - 4))) for x in lines]
    u = Union(range(len(lines)))
    for a in range(len(lines)):
        for b in range(a):
            both = len(sets[a] & sets[b]) if min(len(sets[a]), len(sets[b])) >= 0.8 * max(len(sets[a]), len(sets[b])) else 0
            if both and both >= 0.8 * (len(sets[a]) + len(sets[b]) - both):
                u.join(a, b)
    kept: dict = {}
    for a, n in enumerate(lines):
        kept[u.find(a)] = min(kept.get(u.find(a), first[n]), first[n])
    stay = set(kept.values())
    want = {i: "\n".join(x for k, x in enumerate(t.split("\n")) if len(x.strip(" ")) < 20 or (i, k) in stay) for i, t in rows}
    got = {r["doc_id"]: r["text"] or "" for r in line_dedup.dedup_lines(p).collect()}
    assert sum(got[i] != want[i] for i in want) <= 2  # banding may miss a link


def test_lines_of_repeated_ids_and_clashing_names(spark):
    lines = ["the first long line of text that repeats in two places", "only one document has this second line of words", "a third line, quite unlike the others, is here as well"]
    rows = [(1, lines[0], 1, 2, 3), (5, lines[0] + "\nzz", 1, 2, 3), (5, lines[1] + "\nyy", 1, 2, 3), (5, lines[1] + "\nyy", 1, 2, 3), (7, lines[2], 1, 2, 3)]
    df = spark.createDataFrame(rows, "doc_id long, text string, at int, `_at` int, _dropped int")
    got = sorted((r["doc_id"], r["text"], r["_dropped"]) for r in line_dedup.dedup_lines(df).collect())
    assert got == sorted([(1, lines[0], 0), (5, "zz", 1), (5, lines[1] + "\nyy", 0), (5, lines[1] + "\nyy", 0), (7, lines[2], 0)])
    assert line_dedup.dedup_lines(df).columns == ["doc_id", "text", "at", "_at", "_dropped"]


def test_signed_lines_are_shuffled_once(spark):
    rng = np.random.default_rng(4)
    word = lambda: "".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz"), int(rng.integers(3, 10))))
    words = [word() for _ in range(3000)]
    lines = [" ".join(rng.choice(words, 25)) for _ in range(4000)]
    lines += [f"{x} more" for x in lines[:2000]]
    df = spark.createDataFrame([(len(lines) - i, f"{x}\nshort") for i, x in enumerate(lines)], "doc_id long, text string").repartition(8).localCheckpoint()
    size, before = sum(map(len, lines)), shuffled(spark)
    got = {r["doc_id"]: r["_dropped"] for r in line_dedup.dedup_lines(df).collect()}
    n = len(lines)  # near copies come last here, so their ids are smaller and they stay
    assert sum(got[n - i] for i in range(2000)) >= 1995 and not any(got[n - i] for i in range(2000, n))
    assert shuffled(spark) - before < 3.5 * size


def test_crowded_bands_lose_no_link(spark):
    rng = np.random.default_rng(8)
    word = lambda: "".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz"), int(rng.integers(3, 10))))
    passage = [word() for _ in range(40)]
    lines = []
    for k in range(60):  # lines around one passage, some with a near copy
        own = [word() for _ in range(int(rng.integers(4, 40)))]
        lines.append(" ".join(own + passage))
        if k % 3 == 0:
            lines.append(" ".join(own[1:] + passage))
    sets = [{x[a : a + 5] for a in range(len(x) - 4)} for x in lines]
    u = Union(range(len(lines)))
    for a in range(len(lines)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both >= 0.8 * (len(sets[a]) + len(sets[b]) - both):
                u.join(a, b)
    want = {i: int(u.find(i) != i) for i in range(len(lines))}
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    for crowd in (3, 64):
        got = {r["doc_id"]: r["_dropped"] for r in line_dedup.dedup_lines(df, crowd=crowd).collect()}
        assert sum(got[i] != want[i] for i in want) <= 1 and 5 < sum(want.values()) < 70


def test_lines_around_a_passage_are_told_before_they_are_compared(spark, monkeypatch):
    rng = np.random.default_rng(12)
    word = lambda: "".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz"), int(rng.integers(3, 10))))
    passage = [word() for _ in range(40)]
    lines = [" ".join([word() for _ in range(11)] + passage) for _ in range(100)]
    lines += [f"{x} {word()}" for x in lines[:10]]
    compared, plain = [], line_dedup.similar

    def counted(pairs, *more):
        compared.append(pairs.count())
        return plain(pairs, *more)

    monkeypatch.setattr(line_dedup, "similar", counted)
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    got = {r["doc_id"]: r["_dropped"] for r in line_dedup.dedup_lines(df, crowd=1000).collect()}
    assert [i for i in got if got[i]] == list(range(100, 110))
    assert sum(compared) < 100  # of some 6,000 pairs


def test_copies_of_short_lines(spark):
    rows = [(1, "Read more\n\nsome first text of this page here"), (2, " read more\n\nRead mor\nanother text, about other things"), (3, "x\n \nx\nRead more")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: (r["text"], r["_dropped"]) for r in line_dedup.dedup_lines(df, short_copies=True).collect()}
    assert got == {1: (rows[0][1], 0), 2: ("\nRead mor\nanother text, about other things", 1), 3: ("x\n ", 2)}


def test_short_lines_are_compared_too(spark):
    rng = np.random.default_rng(6)
    runs = lambda x: {x[a : a + 5] for a in range(len(x) - 4)} if len(x) >= 5 else {x}
    lines = ["read more here", "read more here.", "-----", "-------", "abc", "abcd", "read mor", "read more"]
    for _ in range(150):
        x = "".join(rng.choice(list("abcdefgh  "), int(rng.integers(5, 24)))).strip() or "z"
        lines += [x, x[: int(rng.integers(max(1, len(x) - 3), len(x) + 1))] + str(rng.choice(["", "!", " x", "..."]))]
    lines = list(dict.fromkeys(" ".join(x.split(" ")).strip() for x in lines))
    u = Union(range(len(lines)))
    for a in range(len(lines)):
        for b in range(a):
            p, q = runs(lines[a]), runs(lines[b])
            if len(p & q) >= 0.8 * len(p | q) and min(len(lines[a]), len(lines[b])) < 20:
                u.join(a, b)
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    got = {r["doc_id"]: r["_dropped"] for r in line_dedup.dedup_lines(df, min_chars=1).collect()}
    short = [i for i in got if len(lines[i]) < 20]
    assert all(got[i] >= int(u.find(i) != i) for i in short) and sum(got[i] for i in short) >= 20
    assert [got[i] for i in range(8)] == [0, 1, 0, 1, 0, 0, 0, 1]


def test_short_lines_of_the_query(spark, tmp_path):
    rows = [(1, "read more here"), (2, "read more here."), (3, "something else"), (4, " \nabc\nabc")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    assert {r["doc_id"]: r["n_dropped"] for r in queries.op5_line_dedup(spark, str(tmp_path)).collect()} == {1: 0, 2: 1, 3: 0, 4: 1}


def test_near_lines_meet(spark):
    rng = np.random.default_rng(3)
    word = lambda: "".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz"), int(rng.integers(3, 10))))
    runs = lambda x: {x[a : a + 5] for a in range(max(1, len(x) - 4))}
    pairs = [("privacy policy statement", "privacy policy statement."), ("privacy policy settings", "privacy policy settings\r")]
    while len(pairs) < 600:
        words = [word() for _ in range(int(rng.choice([3, 4, 6, 10, 20, 40, 80])))]
        other = list(words)
        for _ in range(int(rng.integers(0, 1 + len(words) // 10))):
            other[int(rng.integers(len(words)))] = word()
        a, b = " ".join(words), " ".join(other) + str(rng.choice(["", ".", "!", "\r", " end"]))
        both = len(runs(a) & runs(b)) / len(runs(a) | runs(b))
        if len(a) >= 20 and a != b and both >= 0.8:
            pairs.append((a, b))
    df = spark.createDataFrame([(2 * k + i, x) for k, ab in enumerate(pairs) for i, x in enumerate(ab)], "doc_id long, text string")
    left = {r["doc_id"]: r["_dropped"] for r in line_dedup.dedup_lines(df).collect()}
    gone = [left[2 * k + 1] for k in range(len(pairs))]
    assert gone[0] == gone[1] == 1 and sum(gone) >= 0.99 * len(pairs)
    assert not any(left[2 * k] for k in range(len(pairs)))


def brute_links(rows, least=0.93):
    ok = [(i, np.array(v, float), l) for i, v, l in rows if l is not None and v and None not in v and np.isfinite(v).all() and any(v)]
    n, u = {i: 0 for i, _, _ in rows}, Union([i for i, _, _ in rows])
    for a in range(len(ok)):
        for b in range(a):
            (i, x, l), (j, y, m) = ok[a], ok[b]
            if l == m and len(x) == len(y) and x @ y / np.sqrt(x @ x) / np.sqrt(y @ y) >= least:
                n[i] += 1
                n[j] += 1
                u.join(i, j)
    return {i: (n[i], u.find(i)) for i in n}


def test_embeddings(spark):
    rng = np.random.default_rng(0)
    centres = rng.normal(size=(6, 8))
    rows = [(i, [float(np.float32(x)) for x in centres[i % 6] + rng.normal(0, 0.25, 8)], int(i % 3)) for i in range(260)]
    rows += [(300 + i, rows[0][1], 0) for i in range(5)]
    rows += [(400, None, 0), (401, [], 0), (402, [0.0] * 8, 0), (403, [float("nan")] * 8, 0), (404, [None] + [1.0] * 7, 0), (405, rows[0][1], None), (406, [1.0, 2.0], 0), (407, [2.0, 4.0], 0), (408, [float("inf")] * 8, 1)]
    df = spark.createDataFrame([(i, v, l, "z", 1.0) for i, v, l in rows], "vec_id long, embedding array<float>, label int, h string, v double")
    want = brute_links([(i, None if v is None else [None if x is None else float(np.float32(x)) for x in v], l) for i, v, l in rows])
    for block in (16, 512):
        got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embed_join.near_duplicates(df, block=block).collect()}
        assert got == want
    assert embed_join.near_duplicates(df.limit(0)).count() == 0
    assert embed_join.near_duplicates(df.where("vec_id >= 400")).count() == 9
    q = queries.op6_embedding_join(spark, SMALL)
    assert q.where("kept != (vec_id = component_id)").count() == 0 and q.count() == 500


def shuffled(spark) -> int:
    """Bytes of shuffles that all stages have written so far."""
    gateway = spark.sparkContext._gateway
    stages = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), None)
    return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))


def test_embeddings_are_not_written_for_each_block_they_meet(spark):
    rng = np.random.default_rng(5)
    v = (rng.normal(size=64) + rng.normal(0, 0.25, (4000, 64))).astype(np.float32)
    v[3000:3500] = v[17]  # copies, over several blocks
    df = spark.createDataFrame([(i, x.tolist(), 0) for i, x in enumerate(v)], "vec_id long, embedding array<float>, label int").repartition(8).localCheckpoint()
    x = v.astype(float)
    x /= np.sqrt((x * x).sum(axis=1, keepdims=True))
    links = x @ x.T
    assert not (abs(links - 0.93) < 1e-12).any()
    want, u = (links >= 0.93).sum(axis=1) - 1, Union(range(len(v)))
    for a, b in zip(*np.nonzero(links >= 0.93)):
        if a < b:
            u.join(int(a), int(b))
    before = shuffled(spark)
    got = {r["vec_id"]: r for r in embed_join.near_duplicates(df, block=128).collect()}
    assert all(got[i]["n_links"] == want[i] and got[i]["component_id"] == u.find(i) for i in range(len(v)))
    assert 0 < shuffled(spark) - before < 4 * v.nbytes


def brute_repeats(rows, length=50):
    first: dict = {}
    for i, b in sorted(rows):
        for s in range(len(b) - length + 1):
            first.setdefault(b[s : s + length], i)
    out = []
    for i, b in rows:
        gone = bytearray(len(b))
        for s in range(len(b) - length + 1):
            if first[b[s : s + length]] < i:
                gone[s : s + length] = b"\1" * length
        spans = sum(1 for k in range(len(b)) if gone[k] and (not k or not gone[k - 1]))
        out.append((i, len(b), sum(gone), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone) if not g)).hexdigest()))
    return sorted(out)


def test_repeats(spark):
    rng = np.random.default_rng(0)
    passage = "".join(rng.choice(list("abcdefgh é"), 180))
    rows = [(i, "".join(rng.choice(list("abcdefghij "), 300)) + passage[: 40 + 5 * i] + "".join(rng.choice(list("klm"), 100)) + passage[30:]) for i in range(30)]
    rows += [(40, None), (41, ""), (42, "x" * 400), (43, "x" * 60), (44, "ab" * 200), (45, passage), (45, passage + "!"), (46, rows[3][1]), (47, passage[:50]), (48, passage[:49])]
    df = spark.createDataFrame([(i, t, 9) for i, t in rows], "doc_id long, text string, g int")
    want = brute_repeats([(i, (t or "").encode()) for i, t in rows])
    for size in (400, 1 << 22):
        got = sorted((r["doc_id"], r["n_bytes"], r["n_removed"], len(r["spans"]), r["kept_sha256"]) for r in repeats.remove_repeats(df, group_bytes=size).collect())
        assert got == want
    assert repeats.remove_repeats(df.limit(0)).count() == 0
    none = repeats.remove_repeats(spark.createDataFrame([(None, passage), (1, passage)], "doc_id long, text string")).collect()
    assert sorted((r["doc_id"] is None, r["n_removed"]) for r in none) == [(False, 0), (True, 0)]


def test_repeats_query(spark):
    docs = [(r["doc_id"], (r["text"] or "").encode()) for r in table(spark, SMALL, "documents").collect()]
    got = sorted(tuple(r) for r in queries.op8_repeats(spark, SMALL).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect())
    assert got == brute_repeats(docs)


def test_equal_ranks_with_other_checks_are_other_strings():
    import numpy as np

    from tsthin.llm import repeats

    row = lambda docs, checks: {
        "ranks": repeats._pack(np.array([7, 9], np.uint64)), "docs": repeats._planes(np.array(docs, np.int64)), "more": repeats._planes(np.array(checks, np.uint16)),
    }
    *_, later, _ = repeats._gathered([row([1, 1], [5, 5]), row([2, 2], [5, 6])], checked=True)
    assert later.tolist() == [False, False, True, False]
