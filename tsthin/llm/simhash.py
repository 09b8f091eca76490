"""SimHash near-duplicate search by the generalised pigeonhole principle.

Fingerprints are cut into partitions of correlated bits. Partition ``i`` gets its own threshold ``t_i >= -1`` with
``sum(t_i) = radius - m + 1``: two fingerprints within the radius must then agree within ``t_i`` in some partition.
The thresholds (and the number of partitions) are those of least estimated cost, found by dynamic programming over
candidate counts measured on all fingerprints. Each fingerprint is indexed by its exact partition values and probes
all values within ``t_i``; candidates are verified on all 64 bits.

Partition values shared by more than ``dense`` distinct fingerprints would give quadratically many candidates. The
fingerprints that touch one are linked through midpoints instead: two fingerprints differ in at most two bits if and
only if some value lies within one bit of both, and at most 65 fingerprints lie within one bit of a value. That way
is exact too and linear; for a radius above two the midpoints are the fingerprints' balls of half the radius.
"""

from __future__ import annotations

from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .support import beside, components, cut, stored

BITS = 64


def fingerprint(text: str | None, words: int = 3, seed: int = 42) -> int:
    """Unsigned 64-bit fingerprint of one text; zero where it has no words (null included)."""
    return majority(run_hashes(text, words, seed))


def run_hashes(text: str | None, words: int, seed: int = 42) -> list[int]:
    """Hashes of all runs of so many words, repeats included; of all words where they are fewer."""
    w = (text or "").encode("utf-8", "replace").lower().split()
    h = xxhash.xxh64_intdigest
    if len(w) < words:
        return [h(b" ".join(w), seed)] if w else []
    return [h(b" ".join(g), seed) for g in zip(*(w[i:] for i in range(words)))]


def majority(hashes: list[int]) -> int:
    """The bits set in over half of the hashes."""
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), 65536):
        block = np.array(hashes[at : at + 65536], dtype=">u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(block, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3) -> DataFrame:
    """``(id_col, fp)``: one row per input row, ``fp`` a signed long. Null and wordless texts give zero."""

    def run(batches):
        for b in batches:
            f = np.array([fingerprint(t, words) for t in b.column(1).to_pylist()], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(f, pa.int64())], names=[id_col, "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, F.col(text_col).cast("string").alias("_t")).mapInArrow(run, f"`{id_col}` {kind}, fp bigint")


def bit_counts(fps: DataFrame) -> tuple[np.ndarray, int]:
    """How often each pair of bits is set together, over all fingerprints: 64 x 64 sums, whatever the input size."""

    def run(batches):
        total, n = np.zeros((BITS, BITS)), 0
        for b in batches:
            v = b.column(0).to_numpy(zero_copy_only=False).astype(">i8").view(np.uint8).reshape(-1, 8)
            for at in range(0, len(v), 65536):
                x = np.unpackbits(v[at : at + 65536], axis=1)[:, ::-1].astype(np.float32)
                total += x.T @ x
            n += len(v)
        if n:
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.arange(BITS * BITS + 1, dtype=np.int32)), pa.array(np.append(total.ravel(), n))], names=["cell", "n"]
            )

    rows = fps.select("fp").mapInArrow(run, "cell int, n double").groupBy("cell").agg(F.sum("n").alias("n")).collect()
    flat = np.zeros(BITS * BITS + 1)
    for r in rows:
        flat[r["cell"]] = r["n"]
    return flat[:-1].reshape(BITS, BITS), int(flat[-1])


def group_bits(counts: np.ndarray, n: int, parts: int) -> list[list[int]]:
    """Cut the 64 bits into ``parts`` groups of near-equal width, correlated bits together."""
    p = np.diag(counts) / max(n, 1)
    cov = counts / max(n, 1) - np.outer(p, p)
    sd = np.sqrt(np.clip(np.diag(cov), 1e-12, None))
    corr = np.abs(cov / np.outer(sd, sd))
    np.fill_diagonal(corr, 0)
    left, out = list(range(BITS)), []
    for i in range(parts):
        width = BITS // parts + (i < BITS % parts)
        group = [max(left, key=lambda b: (corr[b, left].sum(), -b))]
        left.remove(group[0])
        while len(group) < width:
            nxt = max(left, key=lambda b: (corr[b, group].sum(), -b))
            group.append(nxt)
            left.remove(nxt)
        out.append(sorted(group))
    return out


def _key(bits: list[int]):
    key = F.lit(0).cast("long")
    for k, b in enumerate(bits):
        key = key.bitwiseOR(F.shiftleft(F.shiftright(F.col("fp"), b).bitwiseAND(F.lit(1).cast("long")), k))
    return key


def _within(width: int, radius: int) -> list[int]:
    """Masks of at most ``radius`` set bits."""
    return [sum(1 << b for b in c) for e in range(radius + 1) for c in combinations(range(width), e)]


def allocate(cost: list[dict[int, float]], total: int) -> tuple[float, list[int]]:
    """Thresholds of least summed cost with the given sum. ``cost[i]``: threshold to cost, -1 (skipped) to 0 included."""
    best: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for options in cost:
        step: dict[int, tuple[float, list[int]]] = {}
        for spent, (c, ts) in best.items():
            for t, more in options.items():
                if spent + t not in step or c + more < step[spent + t][0]:
                    step[spent + t] = (c + more, [*ts, t])
        best = step
    return best[total]


def plan(fps: DataFrame, radius: int, parts: tuple[int, ...] = (2, 3, 4)) -> list[tuple[list[int], int]]:
    """``(bits, threshold)`` for each partition used, least estimated cost over the numbers of partitions tried."""
    counts, n = bit_counts(fps)
    if not n:
        return []
    p = np.diag(counts) / n
    agree = np.clip(p * p + (1 - p) ** 2, 0.5, 1)
    odds = (1 - agree) / agree
    layouts = {m: group_bits(counts, n, m) for m in parts}
    keys = [F.struct(F.lit(100 * m + i).alias("part"), _key(bits).alias("key")) for m, groups in layouts.items() for i, bits in enumerate(groups)]
    per = fps.select(F.explode(F.array(*keys)).alias("k")).groupBy("k.part", "k.key").agg(F.count("*").alias("n"))
    same = {r["part"]: float(r["s"]) for r in per.groupBy("part").agg(F.sum(F.col("n").cast("double") * F.col("n")).alias("s")).collect()}
    found = []
    for m, groups in layouts.items():
        cost = []
        for i, bits in enumerate(groups):
            poly = np.array([1.0])  # coefficients: expected pairs at 0, 1, ... differing bits, relative to 0
            for b in bits:
                poly = np.convolve(poly, [1.0, odds[b]])[: radius + 1]
            options = {-1: 0.0}
            for t in range(radius + 1):
                probes = sum(comb(len(bits), e) for e in range(t + 1))
                if probes <= 4096:
                    options[t] = n * (1 + probes) + same[100 * m + i] * poly[: t + 1].sum()
            cost.append(options)
        try:
            found.append((*allocate(cost, radius - m + 1), groups))
        except KeyError:
            continue
    _, ts, groups = min(found, key=lambda x: x[0])
    return [(bits, t) for bits, t in zip(groups, ts) if t >= 0]


def links(fps: DataFrame, radius: int = 2, dense: int = 512) -> DataFrame:
    """Links ``(a, b)`` between distinct fingerprints, enough to connect all that are within ``radius`` bits.

    ``fps``: distinct values in column ``fp``, checkpointed by the caller. Pairs met outside dense partition values
    are all given; within them, stars around shared midpoints.
    """
    used = plan(fps, radius)
    if not used:
        return fps.select(F.col("fp").alias("a"), F.col("fp").alias("b")).limit(0)
    index = fps.select("fp", F.explode(F.array(*[F.struct(F.lit(i).alias("part"), _key(bits).alias("key")) for i, (bits, _) in enumerate(used)])).alias("k"))
    index = index.select("k.part", "k.key", F.col("fp").alias("b"))
    probes = None
    for i, (bits, t) in enumerate(used):
        masks = F.array(*[F.lit(x).cast("long") for x in _within(len(bits), t)])
        p = fps.select(F.lit(i).alias("part"), _key(bits).alias("base"), F.col("fp").alias("a"), F.explode(masks).alias("flip"))
        p = p.select("part", F.col("base").bitwiseXOR(F.col("flip")).alias("key"), "a")
        probes = p if probes is None else probes.unionByName(p)
    crowded = cut(index.groupBy("part", "key").agg(F.count("*").alias("n")).where(F.col("n") > dense).select("part", "key"))
    ball = None
    if not crowded.isEmpty():
        near = index.join(crowded, ["part", "key"], "left_semi").select(F.col("b").alias("fp"))
        near = near.unionByName(probes.join(crowded, ["part", "key"], "left_semi").select(F.col("a").alias("fp"))).distinct()
        index = index.join(crowded, ["part", "key"], "left_anti")
        half = F.array(*[F.lit(x - (1 << 64) if x >= 1 << 63 else x).cast("long") for x in _within(BITS, (radius + 1) // 2)])
        mid = near.select("fp", F.explode(half).alias("flip")).select("fp", F.col("fp").bitwiseXOR(F.col("flip")).alias("z"))
        low = mid.groupBy("z").agg(F.min("fp").alias("m"), F.count("*").alias("n")).where("n > 1")
        ball = mid.join(low, "z").where("fp != m").select(F.col("fp").alias("a"), F.col("m").alias("b"))
        if radius % 2 or radius > 2:  # a shared midpoint bounds the distance by twice the ball's radius only
            ball = ball.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius)
    pairs = (
        probes.join(index, ["part", "key"])
        .where((F.col("a") < F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius))
        .select("a", "b")
    )
    return pairs if ball is None else pairs.unionByName(ball)


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, radius: int = 2, dense: int = 512) -> DataFrame:
    """One row per input row: ``id_col``, ``fingerprint`` (16 hex digits), ``component_id`` (smallest id reachable).

    Rows whose fingerprints are equal or linked, directly or through others, share a component. Null texts and texts
    without words have fingerprint zero and link like others; rows with a null id keep their row and get the smallest
    id of their component (null where there is none). Repeated ids give repeated rows. Other columns are ignored.
    """
    if radius > 2 and radius % 2:
        raise ValueError("odd radii above two have no exact midpoint way; take an even one")
    fps = cut(fingerprints(docs, id_col, text_col, words))
    distinct = cut(fps.select("fp").distinct())
    comp = components(links(distinct, radius, dense), "a", "b")
    rooted = fps.join(comp, fps["fp"] == comp["node"], "left").select(id_col, "fp", F.coalesce("component", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min(id_col).alias("component_id"))
    return rooted.join(least, "root").select(id_col, F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


ROWS, BANDS = 4, 16  #: MinHash values of a band, and bands
_RNG = np.random.default_rng(11)
_MIX = _RNG.integers(0, 1 << 63, ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_MASKS = _RNG.integers(0, 1 << 64, (ROWS, BANDS), dtype=np.uint64, endpoint=False)


def shingle_hashes(text: str | None, words: int) -> np.ndarray:
    """Sorted distinct hashes of the runs that ``fingerprint`` counts."""
    return np.unique(np.array(run_hashes(text, words), np.uint64))


def minhash_bands(hashes: np.ndarray) -> list[int]:
    least = np.zeros((ROWS, BANDS), np.uint64)
    if len(hashes):
        for j in range(ROWS):
            x = hashes * _MIX[j]
            x = (x ^ (x >> np.uint64(32))) * _MIX[j]
            least[j] = [(x ^ c).min() for c in _MASKS[j]]
    return [xxhash.xxh64_intdigest(least[:, k].tobytes(), k) - (1 << 63) for k in range(BANDS)]


def fingerprint_pairs(signed: DataFrame, radius: int) -> DataFrame:
    """Pairs ``(a, b)`` of nodes, enough to connect all whose fingerprints are within the radius. ``signed``: ``(node, fp)``."""
    least = stored(signed.groupBy("fp").agg(F.min("node").alias("first")))
    same = signed.join(least, "fp").where(F.col("node") != F.col("first")).select(F.col("node").alias("a"), F.col("first").alias("b"))
    side = lambda n: least.select(F.col("fp").alias(n), F.col("first").alias(f"{n}_first"))
    near = links(least.select("fp"), radius).where("a != b").join(side("a"), "a").join(side("b"), "b")
    return same.unionByName(near.select(F.greatest("a_first", "b_first").alias("a"), F.least("a_first", "b_first").alias("b")))


def _connected(met: DataFrame, compare, near: DataFrame) -> DataFrame:
    """``(node, component)`` of the links that ``compare`` leaves of pairs ``(a, b)``: of ``near``, and those that share a band.

    ``met``: ``(band, node, n, pivot)``.
    """
    others = met.where(F.col("node") != F.col("pivot"))
    to_pivot = others.select(F.greatest("node", "pivot").alias("a"), F.least("node", "pivot").alias("b")).unionByName(near).distinct()
    links = stored(compare(to_pivot))
    # what pivots have connected, in any band, needs no further comparison
    named = stored(components(links, "a", "b"))
    label = lambda n: F.coalesce(f"{n}_label", n)
    side = lambda n: named.select(F.col("node").alias(n), F.col("component").alias(f"{n}_label"))
    more = met.where("n > 2").withColumnRenamed("node", "x").join(side("x"), "x", "left").join(side("pivot"), "pivot", "left")
    more = stored(more.select("band", "x", label("x").alias("x_of"), label("pivot").alias("pivot_of")))
    free = more.where("x_of != pivot_of").select("band", "x", "x_of")
    rest = free.join(more.select("band", F.col("x").alias("y"), F.col("x_of").alias("y_of")), "band").where("x_of != y_of")
    rest = rest.select(F.greatest("x", "y").alias("a"), F.least("x", "y").alias("b")).distinct()
    return components(links.unionByName(compare(rest.join(to_pivot, ["a", "b"], "left_anti"))), "a", "b")


def jaccard_components(docs: DataFrame, id_col: str, text_col: str, words: int, least: float, radius: int = 2) -> DataFrame:
    """``(node, component)`` of ids whose shingles have a Jaccard similarity of at least ``least``, directly or through others.

    Texts whose fingerprints are within ``radius`` bits are found by the search over fingerprints. A radius that holds all
    pairs at 0.8 (some ten bits of 64 differ, often more) holds a part of all pairs, so those further apart meet in MinHash
    bands, at 0.8 with a probability of 0.9998 by the formula. Both are verified exactly. Texts without words are alike.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    named = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("node"), F.col(text_col).cast("string").alias("text"))

    def sign(batches):
        for b in batches:
            marks, bands, sizes = [], [], []
            for t in b.column(1).to_pylist():
                runs = run_hashes(t, words)
                distinct = np.unique(np.array(runs, np.uint64))
                marks.append(majority(runs))
                bands.append(minhash_bands(distinct))
                sizes.append(len(distinct))
            fp = pa.array(np.array(marks, np.uint64).view(np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), fp, pa.array(bands, pa.list_(pa.int64())), pa.array(sizes, pa.int32())], names=["node", "fp", "bands", "size"])

    def verify(batches):
        for b in batches:
            keep = []
            for k, (x, y) in enumerate(zip(b.column(2).to_pylist(), b.column(3).to_pylist())):
                x, y = shingle_hashes(x, words), shingle_hashes(y, words)
                both = len(np.intersect1d(x, y, assume_unique=True))
                if both >= least * (len(x) + len(y) - both):
                    keep.append(k)
            yield b.select([0, 1]).take(pa.array(keep, pa.int64()))

    signed = stored(named.mapInArrow(sign, f"node {kind}, fp bigint, bands array<bigint>, size int"))
    near = stored(fingerprint_pairs(signed.select("node", "fp"), radius).where("a != b").distinct())
    members = signed.select("node", F.explode("bands").alias("band"))
    bands = members.groupBy("band").agg(F.count("*").alias("n"), F.min("node").alias("pivot")).where("n > 1")
    met = stored(members.join(bands, "band").select("band", "node", "n", "pivot"))
    some = met.select("node").union(near.select("a")).union(near.select("b")).distinct()
    texts, sizes = stored(named.join(beside(some), "node", "left_semi")), signed.select("node", "size")

    def compare(pairs):
        side = lambda df, n: df.select(F.col("node").alias(n), F.col(df.columns[1]).alias(f"{n}_x"))
        possible = (F.col("a_x") >= least * F.col("b_x")) & (F.col("b_x") >= least * F.col("a_x"))
        pairs = pairs.join(side(sizes, "a"), "a").join(side(sizes, "b"), "b").where(possible).select("a", "b").distinct()
        found = pairs.join(side(texts, "a"), "a").join(side(texts, "b"), "b").select("a", "b", "a_x", "b_x")
        return found.mapInArrow(verify, f"a {kind}, b {kind}")

    return _connected(met, compare, near)
