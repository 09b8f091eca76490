"""Removal of repeated byte strings by prefix doubling over distributed ranks.

A position's rank at a length names the string of that length that starts there; equal strings have equal ranks. Ranks
are 64-bit fingerprints, since only equality matters. Round one ranks the strings of half the threshold. By the
pigeonhole of sampling, every string of the threshold length holds one of them that is least by fingerprint (its
anchor), and copies hold the same; positions whose anchor occurs in one document only are unique and drop out. So do
the positions of anchors whose surroundings (the run of strings that share the anchor) are the same wherever they
occur: the smallest document with the anchor settles them. Round two doubles: the pair of ranks at a position and half the threshold further gives the rank at the threshold, sorted
among all positions still in play to find the smallest document that holds each string.

Documents are dealt into groups of a given number of bytes. A group sends each rank once, with its smallest document,
as packed sorted arrays to the rank's bucket, and hears one bit back for each. So a passage that a third of all
documents hold costs one entry for each group, and no text is compared or sent beyond the one exchange that forms the groups.
What decides on a removal has 80 bits or more: an anchor of 44 with a shape of 48, or a rank of 64 with a check of 16 that is
computed from the bytes in another way.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = 1 << 18
_BASE = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1
_BYTE = np.random.default_rng(20240501).integers(0, 1 << 64, 256, dtype=np.uint64)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2**64."""
    if n not in _powers:
        _powers.clear()
        with np.errstate(over="ignore"):
            out = []
            for base in (_BASE, pow(_BASE, -1, 1 << 64)):
                p = np.full(n, base, np.uint64)
                p[0] = 1
                out.append(np.cumprod(p))
        _powers[n] = (out[0], out[1])
    return _powers[n]


def ranks(data: np.ndarray, k: int) -> np.ndarray:
    """Fingerprint of each string of ``k`` bytes in at most a block of bytes."""
    up, down = _power_tables(BLOCK + 4096)
    n = len(data)
    s = np.zeros(n + 1, np.uint64)
    np.cumsum(_BYTE[data] * up[:n], out=s[1:])
    h = (s[k:] - s[:-k]) * down[: n - k + 1]
    h ^= h >> np.uint64(31)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(29)
    return h


def _running_min(h: np.ndarray, w: int) -> np.ndarray:
    """Minimum over each ``w`` consecutive values."""
    m, have = h, 1
    while 2 * have <= w:
        m = np.minimum(m[:-have], m[have:])
        have *= 2
    return m if have == w else np.minimum(m[: len(h) - w + 1], m[w - have :])


class Group:
    """The documents of one group, in order of id, and their ranks. A window is a string of the threshold length within a document."""

    def __init__(self, ids: list, texts: list, length: int):
        order = sorted(range(len(ids)), key=lambda i: ids[i])
        self.length, self.half = length, length // 2
        self.ids = np.array([ids[i] for i in order], dtype=np.int64)
        self.data = [(texts[i] or "").encode("utf-8", "replace") for i in order]
        # documents of one id are one document: the owner is the first row of the id
        self.owner = np.searchsorted(self.ids, self.ids)
        values, owners, counts, shapes, pairs, piece_rows, piece_starts, piece_counts = [], [], [], [], [], [], [], []
        for rows, spans, buffer in self._pieces():
            data = np.frombuffer(buffer, np.uint8)
            h = ranks(data, self.half)
            least = _running_min(h, length - self.half + 1) >> np.uint64(20)
            shift = length - self.half
            pair = h[: len(least)] * np.uint64(0x9FB21C651E98DF25) + (h[shift : shift + len(least)] ^ np.uint64(0x2545F4914F6CDD1D))
            pair ^= pair >> np.uint64(32)
            pair *= np.uint64(0xD6E8FEB86659FD93)
            pair ^= pair >> np.uint64(32)
            lens = np.array([e - s for s, e in spans])
            begin = np.cumsum(lens) - lens
            inside = np.zeros(len(data) + 1, np.int8)
            np.add.at(inside, begin, 1)
            np.add.at(inside, begin + lens - length + 1, -1)
            inside = np.cumsum(inside, dtype=np.int8)[: len(least)].astype(bool)
            least, n = least[inside], lens - length + 1
            new = np.ones(len(least), bool)  # runs of windows with one anchor in one piece
            new[1:] = least[1:] != least[:-1]
            new[np.cumsum(n) - n] = True
            at = np.nonzero(new)[0]
            values.append(least[at])
            counts.append(np.diff(np.append(at, len(least))))
            owners.append(self.owner[np.repeat(np.array(rows), n)[at]])
            # a run's first and last string cover all its bytes unless it is long; 0 stands for those
            own = pair[inside]
            last = own[at + counts[-1] - 1]
            shape = own[at] * np.uint64(0xA24BAED4963EE407) + (last ^ np.uint64(0x9E6C63D0876A9A62)) + counts[-1].astype(np.uint64)
            shape ^= shape >> np.uint64(29)
            shape = (shape * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(16) | np.uint64(1)
            shapes.append(np.where(counts[-1] <= length, shape, np.uint64(0)))
            pairs.append(own)
            piece_rows += rows
            piece_starts += [s for s, _ in spans]
            piece_counts.append(n)
        join = lambda x, t: np.concatenate(x) if x else np.zeros(0, t)
        self.value, self.run_owner, self.run_length, self.pair = join(values, np.uint64), join(owners, np.int64), join(counts, np.int64), join(pairs, np.uint64)
        self.shape = join(shapes, np.uint64)
        self.piece_rows, self.piece_starts = np.array(piece_rows, np.int64), np.array(piece_starts, np.int64)
        self.piece_end = np.cumsum(join(piece_counts, np.int64))

    def place(self, windows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row and start of windows given by their indices."""
        piece = np.searchsorted(self.piece_end, windows, side="right")
        before = np.append(0, self.piece_end)[piece]
        return self.piece_rows[piece], self.piece_starts[piece] + windows - before

    def _pieces(self):
        """Buffers of about a block: whole documents, or overlapping pieces of a long one."""
        rows, spans, parts, size = [], [], [], 0
        for r, d in enumerate(self.data):
            if len(d) < self.length:
                continue
            for at in range(0, len(d) - self.length + 1, BLOCK // 2):
                piece = d[at : at + BLOCK // 2 + self.length - 1]
                if size + len(piece) > BLOCK:
                    yield rows, spans, b"".join(parts)
                    rows, spans, parts, size = [], [], [], 0
                rows.append(r)
                spans.append((at, at + len(piece)))
                parts.append(piece)
                size += len(piece)
        if parts:
            yield rows, spans, b"".join(parts)

    def anchors(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Distinct anchors, the smallest document row of each, the shape of its runs (0: they differ or are long), whether two documents here hold it, and for each run the index of its anchor."""
        u, inverse = np.unique(self.value, return_inverse=True)
        least, most = np.full(len(u), len(self.ids)), np.full(len(u), -1)
        np.minimum.at(least, inverse, self.run_owner)
        np.maximum.at(most, inverse, self.run_owner)
        lo, hi = np.full(len(u), _MASK, np.uint64), np.zeros(len(u), np.uint64)
        np.minimum.at(lo, inverse, self.shape)
        np.maximum.at(hi, inverse, self.shape)
        return u, least, np.where(lo == hi, lo, np.uint64(0)), most != least, inverse

    def checks(self, windows: np.ndarray) -> np.ndarray:
        """16 bits of the bytes of each window, by a polynomial that shares nothing with the ranks."""
        out = np.empty(len(windows), np.uint16)
        whole, begin = np.frombuffer(b"".join(self.data), np.uint8), np.cumsum([0] + [len(d) for d in self.data])
        for at in range(0, len(windows), BLOCK):
            rows, starts = self.place(windows[at : at + BLOCK])
            first = begin[rows] + starts
            c = np.full(len(first), 0x1B873593, np.uint64)
            for k in range(self.length):
                c = (c ^ whole[first + k]) * np.uint64(0xD1342543DE82EF95)
                c ^= c >> np.uint64(32)
            out[at : at + BLOCK] = c & np.uint64(0xFFFF)
        return out

    def strings(self, active: np.ndarray, checked: bool = False) -> tuple[np.ndarray, ...]:
        """Distinct ranks at full length of the windows of active runs, the smallest document row of each, and those windows with their indices, or with ``checked`` the check of each rank."""
        w = np.nonzero(np.repeat(active, self.run_length))[0]
        order = np.argsort(self.pair[w], kind="stable")  # windows come in order of document
        sorted_ = self.pair[w][order]
        new = np.ones(len(w), bool)
        new[1:] = sorted_[1:] != sorted_[:-1]
        first = w[order][new]
        values, least = sorted_[new], self.owner[self.place(first)[0]] if len(w) else np.zeros(0, np.int64)
        if checked:
            del w, order, sorted_, new
            return values, least, self.checks(first)
        index = np.empty(len(w), np.int64)
        index[order] = np.cumsum(new) - 1
        return values, least, w, index


def _pack(x: np.ndarray) -> bytes:
    """Sorted unsigned integers as differences, byte plane by byte plane, so that compression sees the empty planes."""
    d = np.diff(x, prepend=x.dtype.type(0))
    return np.ascontiguousarray(d.view(np.uint8).reshape(len(d), -1).T).tobytes()


def _unpack(b: bytes, dtype) -> np.ndarray:
    width = np.dtype(dtype).itemsize
    d = np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(width, -1).T).view(dtype).ravel()
    return np.cumsum(d, dtype=dtype)


def _planes(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x.view(np.uint8).reshape(len(x), -1).T).tobytes()


def _from_planes(b: bytes, dtype) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(np.dtype(dtype).itemsize, -1).T).view(dtype).ravel()


def _buckets(values: np.ndarray, bits: int, buckets: int) -> np.ndarray:
    """Bounds of each bucket in sorted values of so many bits."""
    edges = [(b << bits) // buckets for b in range(buckets)]
    return np.append(np.searchsorted(values, np.array(edges, dtype=np.uint64)), len(values))


def _blobs(group: int, values, docs, bits: int, buckets: int, more=None) -> pa.Table:
    """``more``: what tells equal values apart, shapes of anchors or checks of strings."""
    at = _buckets(values, bits, buckets)
    rows = [b for b in range(buckets) if at[b] < at[b + 1]]
    cut = lambda x, b: x[at[b] : at[b + 1]]
    return pa.table(
        {
            "bucket": pa.array(rows, pa.int32()),
            "g": pa.array([group] * len(rows), pa.int64()),
            "ranks": pa.array([_pack(cut(values, b)) for b in rows], pa.binary()),
            "docs": pa.array([_planes(cut(docs, b)) for b in rows], pa.binary()),
            "more": pa.array([None if more is None else _planes(cut(more, b)) for b in rows], pa.binary()),
        }
    )


def _answer(rows, flags: list[np.ndarray], turn: int) -> pa.Table:
    return pa.table(
        {
            "g": pa.array([r["g"] for r in rows], pa.int64()),
            "turn": pa.array([turn] * len(rows), pa.int32()),
            "bucket": pa.array([r["bucket"] for r in rows], pa.int32()),
            "bits": pa.array([np.packbits(f).tobytes() for f in flags], pa.binary()),
        }
    )


def _heard(answers: list[dict], turn: int, values: np.ndarray, bits: int, buckets: int) -> np.ndarray:
    at, out = _buckets(values, bits, buckets), np.zeros(len(values), bool)
    for r in answers:
        if r["turn"] == turn:
            lo, hi = at[r["bucket"]], at[r["bucket"] + 1]
            out[lo:hi] = np.unpackbits(np.frombuffer(r["bits"], np.uint8))[: hi - lo]
    return out


def _gathered(rows: list[dict], checked: bool = False):
    """Entries of one bucket from all groups: values, documents and the sizes of the groups' shares, then where the values' runs begin in sorted order.

    With ``checked`` a run is of equal values and equal checks."""
    values, ids = [_unpack(r["ranks"], np.uint64) for r in rows], [_from_planes(r["docs"], np.int64) for r in rows]
    v, d = np.concatenate(values), np.concatenate(ids)
    order = np.lexsort((d, v))
    new = np.ones(len(v), bool)
    new[1:] = v[order][1:] != v[order][:-1]
    if checked and len(v):
        c = np.concatenate([_from_planes(r["more"], np.uint16) for r in rows])
        at = np.nonzero(new)[0]
        if (np.minimum.reduceat(c[order], at) != np.maximum.reduceat(c[order], at)).any():  # two strings of one rank
            order = np.lexsort((d, c, v))
            new[1:] = (v[order][1:] != v[order][:-1]) | (c[order][1:] != c[order][:-1])
    start = np.nonzero(new)[0]
    later = np.empty(len(v), bool)
    later[order] = d[order] > d[order][start][np.cumsum(new) - 1]
    return order, start, np.cumsum(new) - 1, later, np.cumsum([len(x) for x in values])[:-1]


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 50, group_bytes: int = 4 << 20) -> DataFrame:
    """``(id_col, n_bytes, n_removed, spans, kept_sha256)``: one row per input row.

    A byte is removed if a string of ``length`` bytes that covers it also starts in a document with a smaller id.
    ``spans`` are the maximal removed runs (byte offsets in UTF-8, end exclusive), judged on the input. Null texts are
    empty; shorter texts lose nothing; rows that repeat an id are one document for comparison and a row each in the
    result; rows with a null id lose nothing and take nothing away. Ids must be integers. Other columns are ignored.
    A group's arrays take some twenty times ``group_bytes``, or the longest text if that is larger.
    """
    if length < 2 or length % 2:
        raise ValueError("the threshold is doubled to: it must be even")
    total = docs.agg(F.sum(F.octet_length(text_col).cast("long"))).first()[0] or 0
    groups = max(1, -(-total // group_bytes))
    buckets = int(min(groups, 1 << 20))
    kind = docs.schema[id_col].dataType.simpleString()
    dealt = docs.select(
        F.when(F.col(id_col).isNull(), F.lit(-1).cast("long")).otherwise(F.pmod(F.xxhash64(id_col), F.lit(groups))).alias("g"), F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")
    )
    blob = "bucket int, g long, ranks binary, docs binary, more binary"
    answer = "g long, turn int, bucket int, bits binary"
    nothing = np.zeros(0, np.uint64), np.zeros(0, np.int64)

    def load(t: pa.Table) -> Group:
        return Group(t.column("id").to_pylist(), t.column("text").to_pylist(), length)

    def say_anchors(t: pa.Table) -> pa.Table:
        g = t.column("g")[0].as_py()
        if g < 0:
            return _blobs(g, *nothing, 44, buckets)
        x = load(t)
        u, least, shape, _, _ = x.anchors()
        return _blobs(g, u, x.ids[least], 44, buckets, shape)

    def judge_anchors(t: pa.Table) -> pa.Table:
        """Turn 1: the anchor's runs differ between groups or within one; turn 2: they don't, and a smaller document has it."""
        rows = t.to_pylist()
        order, start, run, later, sizes = _gathered(rows)
        shape = np.concatenate([_from_planes(r["more"], np.uint64) for r in rows])[order]
        lo, hi = np.minimum.reduceat(shape, start), np.maximum.reduceat(shape, start)
        mixed = np.empty(len(order), bool)
        several = np.diff(np.append(start, len(order))) > 1
        mixed[order] = (several & ((lo != hi) | (lo == 0)))[run]
        return pa.concat_tables([_answer(rows, np.split(mixed, sizes), 1), _answer(rows, np.split(later & ~mixed, sizes), 2)])

    def settled(x: Group, answers: list[dict]):
        """Runs to be compared string by string, and runs that go as they are."""
        u, least, shape, twice, index = x.anchors()
        open_ = _heard(answers, 1, u, 44, buckets) | twice & (shape == 0)
        if not len(index):
            return np.zeros(0, bool), np.zeros(0, bool)
        return open_[index], ~open_[index] & (_heard(answers, 2, u, 44, buckets)[index] | (x.run_owner > least[index]))

    def say_strings(t: pa.Table, said: pa.Table) -> pa.Table:
        if not len(t) or t.column("g")[0].as_py() < 0:
            return _blobs(-1, *nothing, 64, buckets)
        x = load(t)
        values, least, checks = x.strings(settled(x, said.to_pylist())[0], checked=True)
        return _blobs(t.column("g")[0].as_py(), values, x.ids[least], 64, buckets, checks)

    def judge_strings(t: pa.Table) -> pa.Table:
        rows = t.to_pylist()
        *_, later, sizes = _gathered(rows, checked=True)
        return _answer(rows, np.split(later, sizes), 3)

    names = [id_col, "n_bytes", "n_removed", "spans", "kept_sha256"]
    spans_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def cut_out(t: pa.Table, said: pa.Table) -> pa.Table:
        out = []
        if len(t) and t.column("g")[0].as_py() < 0:
            for s in t.column("text").to_pylist():
                b = (s or "").encode("utf-8", "replace")
                out.append((None, len(b), 0, [], hashlib.sha256(b).hexdigest()))
        elif len(t):
            x, answers = load(t), said.to_pylist()
            open_, whole = settled(x, answers)
            values, least, w, index = x.strings(open_)
            later = _heard(answers, 3, values, 64, buckets)
            gone = np.repeat(whole, x.run_length)
            if len(w):
                gone[w] = later[index] | (x.owner[x.place(w)[0]] > least[index])
            gone = np.nonzero(gone)[0]
            rows, starts = x.place(gone) if len(gone) else (gone, gone)
            bounds = np.searchsorted(rows, np.arange(len(x.ids) + 1))
            for r, data in enumerate(x.data):
                s = starts[bounds[r] : bounds[r + 1]]
                spans = []
                if len(s):
                    s = np.sort(s)
                    cuts = np.nonzero(np.diff(s) > length)[0]
                    spans = list(zip(s[np.append(0, cuts + 1)].tolist(), (s[np.append(cuts, len(s) - 1)] + length).tolist()))
                digest, at = hashlib.sha256(), 0
                for a, b in spans:
                    digest.update(data[at:a])
                    at = b
                digest.update(data[at:])
                out.append((int(x.ids[r]), len(data), sum(b - a for a, b in spans), [{"start": a, "end": b} for a, b in spans], digest.hexdigest()))
        cols = list(zip(*out)) if out else [()] * 5
        types = [pa.int64(), pa.int64(), pa.int64(), spans_type, pa.string()]
        return pa.table([pa.array(c, k) for c, k in zip(cols, types)], names=names)

    first = dealt.groupBy("g").applyInArrow(say_anchors, blob).groupBy("bucket").applyInArrow(judge_anchors, answer)
    second = dealt.groupBy("g").cogroup(first.groupBy("g")).applyInArrow(say_strings, blob).groupBy("bucket").applyInArrow(judge_strings, answer)
    schema = f"`{id_col}` bigint, n_bytes bigint, n_removed bigint, spans array<struct<start:bigint,end:bigint>>, kept_sha256 string"
    done = dealt.groupBy("g").cogroup(first.unionByName(second).groupBy("g")).applyInArrow(cut_out, schema)
    return done.withColumn(id_col, F.col(id_col).cast(kind))
