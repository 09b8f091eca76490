"""Embedding near-duplicates by an epsilon grid order join.

Unit vectors are projected on their leading principal directions, laid on a grid of cell width epsilon and sorted in
grid order within their label. The sorted sequence is cut into blocks; block pairs whose bounding boxes are farther
apart than epsilon are never met, pairs that are met are split again and again, skipping halves that are provably
distant, down to small leaves that are compared in double precision. A block pair gives counts of links for each
vector and a spanning forest of its links, so that dense groups give no quadratic output.

Blocks are written once, to the shared folder, with their vectors as given; pairs of blocks are read from there
(a product of partitions), so no vector is shuffled for each block that its own one meets.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .support import components, cut

SLACK = 1e-9  #: of box distances, for rounding: far above the error of projections, far below any distance that matters
LEAF = 64
PART = 16 << 20  #: bytes of vectors in a partition of blocks
COPIES = 1 << 16  #: copies that a block names; further ones start a block of their own


def _by_width(lists: pa.Array) -> list[tuple[np.ndarray, np.ndarray]]:
    """``(rows, vectors)`` for each width; rows that are null, empty, zero or hold null or non-finite components are left out."""
    lengths = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    values = lists.flatten().to_numpy(zero_copy_only=False)  # nulls become NaN
    starts, out = np.cumsum(lengths) - lengths, []
    for w in np.unique(lengths[lengths > 0]).tolist():
        rows = np.nonzero(lengths == w)[0]
        x = values[starts[rows][:, None] + np.arange(w)]
        ok = np.isfinite(x).all(axis=1) & (x != 0).any(axis=1)
        out.append((rows[ok], x[ok]))
    return out


def _unit(x: np.ndarray) -> np.ndarray:
    """Rows scaled to length one, in double precision."""
    x = x.astype(np.float64)
    x /= np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt(np.einsum("ij,ij->i", x, x))[:, None]


def _moments(vectors: DataFrame) -> tuple[np.ndarray, np.ndarray, int, int] | None:
    """Sum, second moments and count of the vectors of the commonest width, and bytes of all; the collected size depends on widths alone.

    ``vectors``: column ``v`` of lists; those that link with nothing are left out.
    """

    def run(batches):
        total = {}
        for b in batches:
            for _, x in _by_width(b.column(0)):
                x = _unit(x)
                n, s, m = total.get(x.shape[1], (0, 0.0, 0.0))
                total[x.shape[1]] = n + len(x), s + x.sum(axis=0), m + x.T @ x
        for d, (n, s, m) in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([d]), pa.array([n]), pa.array([s.tobytes()], pa.binary()), pa.array([m.tobytes()], pa.binary())], names=["d", "n", "s", "m"])

    def add(batches):
        total = {}
        for b in batches:
            for r in b.to_pylist():
                s, m = np.frombuffer(r["s"]).copy(), np.frombuffer(r["m"]).copy()
                old = total.get(r["d"])
                total[r["d"]] = (r["n"], s, m) if old is None else (old[0] + r["n"], old[1] + s, old[2] + m)
        for d, (n, s, m) in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([d]), pa.array([n]), pa.array([s.tobytes()], pa.binary()), pa.array([m.tobytes()], pa.binary())], names=["d", "n", "s", "m"])

    schema = "d bigint, n bigint, s binary, m binary"
    rows = vectors.select("v").mapInArrow(run, schema).coalesce(8).mapInArrow(add, schema).collect()
    if not rows:
        return None
    counts: dict[int, int] = {}
    for r in rows:
        counts[r["d"]] = counts.get(r["d"], 0) + r["n"]
    d = max(counts, key=lambda k: (counts[k], k))  # the commonest width; others are compared without projections
    size = sum(8 * k * n for k, n in counts.items())
    rows = [r for r in rows if r["d"] == d]
    return sum(np.frombuffer(r["s"]) for r in rows), sum(np.frombuffer(r["m"]).reshape(d, d) for r in rows), sum(r["n"] for r in rows), size


def directions(vectors: DataFrame, dims: int) -> tuple[np.ndarray, int]:
    """Leading principal directions (rows) of the unit vectors, over all of them, and the bytes of these."""
    found = _moments(vectors)
    if found is None:
        return np.zeros((0, 0)), 0
    s, m, n, size = found
    _, axes = np.linalg.eigh(m / n - np.outer(s / n, s / n))
    return np.ascontiguousarray(axes[:, ::-1][:, :dims].T), size


def _forest(a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
    """Spanning forest of the edges (a[i], b[i]) over small integers."""
    up: dict[int, int] = {}

    def find(x: int) -> int:
        while up.setdefault(x, x) != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    out = []
    for x, y in zip(a.tolist(), b.tolist()):
        p, q = find(x), find(y)
        if p != q:
            up[max(p, q)] = min(p, q)
            out.append((x, y))
    return out


def _meet(x, px, y, py, eps2, least, same, hit):
    """Recursive join of two sequence intervals; calls hit(ix, iy) with index arrays of linked vectors."""

    def go(i0, i1, j0, j1):
        if same and j1 <= i0:
            return
        gap = np.maximum(0, np.maximum(px[i0:i1].min(0) - py[j0:j1].max(0), py[j0:j1].min(0) - px[i0:i1].max(0)))
        if float(gap @ gap) > eps2 + SLACK:
            return
        if i1 - i0 <= LEAF and j1 - j0 <= LEAF:
            a, b = np.nonzero(x[i0:i1] @ y[j0:j1].T >= least)
            a, b = a + i0, b + j0
            if same:
                keep = a < b
                a, b = a[keep], b[keep]
            if len(a):
                hit(a, b)
        elif i1 - i0 >= j1 - j0:
            mid = (i0 + i1) // 2
            go(i0, mid, j0, j1)
            go(mid, i1, j0, j1)
        else:
            mid = (j0 + j1) // 2
            go(i0, i1, j0, mid)
            go(i0, i1, mid, j1)

    go(0, len(x), 0, len(y))


def near_duplicates(
    rows: DataFrame,
    id_col: str = "vec_id",
    vec_col: str = "embedding",
    label_col: str = "label",
    least: float = 0.93,
    dims: int = 6,
    block: int = 2048,
) -> DataFrame:
    """One row per input row: ``id_col``, ``n_links``, ``component_id``, ``kept``.

    Two vectors link if their labels are equal and not null, their widths are equal and their cosine in double
    precision is at least ``least`` (above 0). Vectors that are null, empty, zero or hold null or non-finite components
    link with nothing, as do rows with a null label or id. Copies that meet in a partition are one vector that carries its number of
    rows. Component ids are the smallest ids reachable; unlinked rows are components of their own. Ids are taken to be
    distinct: rows that repeat an id are other vectors that share it.
    """
    eps2 = 2 - 2 * least
    eps = math.sqrt(eps2)
    single = rows.schema[vec_col].dataType == T.ArrayType(T.FloatType(), rows.schema[vec_col].dataType.containsNull)
    dtype = np.dtype("<f4" if single else "<f8")
    vec = F.col(vec_col) if single else F.col(vec_col).cast("array<double>")
    raw = rows.select(F.col(id_col).cast("long").alias("_id"), F.col(label_col).cast("long").alias("_l"), vec.alias("v")).where("_id is not null and _l is not null and v is not null")
    axes, size = directions(raw.select("v"), dims)
    if not len(axes):
        lone = F.lit(0).cast("long").alias("n_links")
        return rows.select(id_col, lone, F.col(id_col).cast("long").alias("component_id"), F.lit(True).alias("kept"))
    d = axes.shape[1]
    parts = max(8, -(-size // PART))

    def projected(x: np.ndarray) -> np.ndarray:
        return x @ axes.T if x.shape[1] == d else np.zeros((len(x), len(axes)))

    def place(batches):
        """The cell of every vector as bytes in grid order; rows that link with nothing go."""
        for b in batches:
            for at, x in _by_width(b.column(2)):
                if len(at):
                    cells = np.floor(projected(_unit(x)) / eps).astype(np.int64) + (1 << 31)
                    k, at = cells.astype(">u4"), pa.array(at)
                    packed = lambda y: pa.array([r.tobytes() for r in y], pa.binary())
                    yield pa.RecordBatch.from_arrays([b.column(0).take(at), b.column(1).take(at), packed(k), packed(x.astype(dtype))], names=["_id", "_l", "cell", "v"])

    placed = raw.mapInArrow(place, "_id bigint, _l bigint, cell binary, v binary").withColumn("width", F.length("v")).withColumn("h", F.xxhash64("v"))
    names = ["_l", "width", "cell", "h", "v", "_id"]
    sorted_ = placed.repartitionByRange(parts, *names[:4], "_id").sortWithinPartitions(*names)

    def blocks(batches):
        """Consecutive runs of one label and width, at most ``block`` long, each as one row; copies fall together."""
        number, serial = TaskContext.get().partitionId() << 32, 0
        at, held, copies, named = None, [], [], 0

        def row():
            nonlocal held, copies, named, serial
            x = b"".join(v for _, v in held)
            p = projected(_unit(np.frombuffer(x, dtype).reshape(len(held), -1)))
            many = [k for k, c in enumerate(copies) if c]
            out = {
                "block": number + serial, "_l": at[0], "width": at[1], "lo": p.min(0).tolist(), "hi": p.max(0).tolist(), "reps": [i for i, _ in held], "copies": [1 + len(c) for c in copies],
                "v": x, "same": [{"rep": held[k][0], "ids": copies[k]} for k in many],
            }
            held, copies, named, serial = [], [], 0, serial + 1
            return out

        same = pa.list_(pa.struct([("rep", pa.int64()), ("ids", pa.list_(pa.int64()))]))
        schema = pa.schema([("block", pa.int64()), ("_l", pa.int64()), ("width", pa.int32()), ("lo", pa.list_(pa.float64())), ("hi", pa.list_(pa.float64())), ("reps", pa.list_(pa.int64())), ("copies", pa.list_(pa.int32())), ("v", pa.binary()), ("same", same)])
        for b in batches:
            out = []
            for i, label, width, v in zip(*(b.column(c).to_pylist() for c in range(4))):
                if held and ((label, width) != at or named >= COPIES or (len(held) >= block and held[-1][1] != v)):
                    out.append(row())
                at = label, width
                if held and held[-1][1] == v:
                    copies[-1].append(i)
                    named += 1
                else:
                    held.append((i, v))
                    copies.append([])
            if out:
                yield pa.RecordBatch.from_pylist(out, schema)
        if held:
            yield pa.RecordBatch.from_pylist([row()], schema)

    made = sorted_.select("_id", "_l", "width", "v").mapInArrow(
        blocks, "block bigint, _l bigint, width int, lo array<double>, hi array<double>, reps array<bigint>, copies array<int>, v binary, same array<struct<rep: bigint, ids: array<bigint>>>"
    )
    made = cut(made)

    # block pairs: those of one label and width that lie within epsilon on the principal axes. Both sides of the product
    # are read from the checkpoint; an equality would make it a join that writes all blocks once for each that they meet
    few = made.coalesce(parts)
    side = lambda n: few.select(F.col("block").alias(n), *[F.col(c).alias(f"{n}_{c}") for c in ("_l", "width", "lo", "hi", "reps", "copies", "v")])
    far = lambda i: F.greatest(F.lit(0.0), F.element_at("a_lo", i + 1) - F.element_at("b_hi", i + 1), F.element_at("b_lo", i + 1) - F.element_at("a_hi", i + 1))
    gap = sum(far(i) * far(i) for i in range(len(axes)))
    alike = (F.col("a__l") <= F.col("b__l")) & (F.col("a__l") >= F.col("b__l")) & (F.col("a_width") <= F.col("b_width")) & (F.col("a_width") >= F.col("b_width"))
    met = side("a").hint("shuffle_replicate_nl").join(side("b"), (F.col("a") <= F.col("b")) & alike & (gap <= eps2 + SLACK))
    work = met.select("a", "b", *[f"{n}_{c}" for n in "ab" for c in ("reps", "copies", "v")])

    def compare(batches):
        for b in batches:
            for k in range(b.num_rows):
                part = {n: b.column(n)[k] for n in b.schema.names}
                ra, rb, ca, cb = (part[n].values.to_numpy() for n in ("a_reps", "b_reps", "a_copies", "b_copies"))
                n, m = len(ra), len(rb)
                x, y = (_unit(np.frombuffer(part[c].as_py(), dtype).reshape(k_, -1)) for c, k_ in (("a_v", n), ("b_v", m)))
                same = part["a"].as_py() == part["b"].as_py()
                ca, cb = ca.astype(np.int64), cb.astype(np.int64)
                na, nb = np.zeros(n, np.int64), np.zeros(m, np.int64)
                edges: list[tuple[int, int]] = []
                if same:
                    na += ca - 1

                def hit(i, j, na=na, nb=nb, ca=ca, cb=cb, edges=edges, n=n, same=same):
                    np.add.at(na, i, cb[j])
                    np.add.at(na if same else nb, j, ca[i])
                    edges += _forest(i, j if same else j + n)

                _meet(x, projected(x), y, projected(y), eps2, least, same, hit)
                ids = ra if same else np.concatenate([ra, rb])
                counts = na if same else np.concatenate([na, nb])
                e = np.array(edges, dtype=np.int64).reshape(-1, 2)
                e = np.array(_forest(e[:, 0], e[:, 1]), dtype=np.int64).reshape(-1, 2)
                some = counts > 0
                zero = np.zeros(len(e), np.int64)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.concatenate([ids[e[:, 0]], ids[some]])), pa.array(np.concatenate([ids[e[:, 1]], ids[some]])), pa.array(np.concatenate([zero, counts[some]]))],
                    names=["a", "b", "n"],
                )

    found = cut(work.mapInArrow(compare, "a bigint, b bigint, n bigint"))
    comp = components(found.where("n = 0"), "a", "b")
    counts = found.where("n > 0").groupBy(F.col("a").alias("node")).agg(F.sum("n").alias("n"))
    per = counts.withColumn("component", F.lit(None).cast("long")).unionByName(comp.select("node", F.lit(0).cast("long").alias("n"), "component"))
    per = per.groupBy("node").agg(F.sum("n").alias("n"), F.min("component").alias("component"))
    # copies are unfolded after the join, so that a large group is one row in it
    same = made.select(F.explode("same").alias("s")).select(F.col("s.rep").alias("rep"), "s.ids").join(per, F.col("rep") == F.col("node"))
    same = same.select(F.explode("ids").alias("node"), "n", F.coalesce("component", "rep").alias("component"))
    # rows that repeat an id share what it has
    told = per.unionByName(same).groupBy("node").agg(F.max("n").alias("n"), F.min("component").alias("component"))
    joined = rows.select(id_col).join(told, F.col(id_col).cast("long") == F.col("node"), "left")
    return joined.select(
        id_col,
        F.coalesce("n", F.lit(0).cast("long")).alias("n_links"),
        F.coalesce("component", F.col(id_col).cast("long")).alias("component_id"),
    ).withColumn("kept", F.coalesce(F.col(id_col) == F.col("component_id"), F.lit(True)))
