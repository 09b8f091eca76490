"""Language identification by hierarchical discrimination: the family first, then one against one within it.

Features are hashed byte n-grams (1 to 3) of the lower-cased text, square-rooted and scaled to length one. A linear
one-against-one vote over families comes first; within the family, one linear support vector machine for each pair of
languages. The machines are trained here, on a bounded sample of labelled rows.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WIDTH = 4096
#: Families of closely related languages, fixed values; a language named in none is a family of its own.
FAMILIES = {
    "germanic": ("en", "de", "nl", "sv", "da", "no"),
    "romance": ("fr", "es", "it", "pt", "ro", "ca"),
    "slavic": ("ru", "pl", "cs", "uk", "bg", "sr"),
}


def family_of(lang: str) -> str:
    return next((f for f, members in FAMILIES.items() if lang in members), lang)


def features(text: str) -> np.ndarray:
    """Unit vector of hashed n-gram counts of the whole text."""
    b = np.frombuffer(text.lower().encode("utf-8", "replace"), dtype=np.uint8).astype(np.uint32)
    total = np.zeros(WIDTH)
    for at in range(0, len(b), 1 << 20):
        x = b[max(0, at - 2) : at + (1 << 20)]
        fresh = at - max(0, at - 2)
        total += np.bincount((x[fresh:] * np.uint32(2654435761)) >> np.uint32(20), minlength=WIDTH)
        two = x[:-1] * np.uint32(2246822519) + x[1:] * np.uint32(3266489917)
        total += np.bincount(two[max(0, fresh - 1) :] >> np.uint32(20), minlength=WIDTH)
        three = x[:-2] * np.uint32(668265263) + x[1:-1] * np.uint32(374761393) + x[2:] * np.uint32(2654435761)
        total += np.bincount((three ^ (three >> np.uint32(15))) * np.uint32(2246822519) >> np.uint32(20), minlength=WIDTH)
    v = np.sqrt(total)
    return v / (np.sqrt(float(v @ v)) or 1.0)


def svm(x: np.ndarray, y: np.ndarray, reg: float = 1e-4, epochs: int = 12, seed: int = 7) -> np.ndarray:
    """Linear support vector machine by averaged stochastic subgradients in small batches; weights, then the bias."""
    x = np.hstack([x, np.ones((len(x), 1), x.dtype)])
    w, mean, t = np.zeros(x.shape[1]), np.zeros(x.shape[1]), 0
    rng = np.random.default_rng(seed)
    for epoch in range(epochs):
        for rows in np.array_split(rng.permutation(len(x)), max(1, len(x) // 16)):
            t += 1
            bad = rows[y[rows] * (x[rows] @ w) < 1]
            step = 1 / (reg * (t + 1000))
            w *= 1 - step * reg
            if len(bad):
                w += step * (y[bad] @ x[bad]) / len(rows)
            if epoch:
                mean += (w - mean) / (t - len(x) // 16 or 1)
    return mean


@dataclass
class Model:
    families: list[tuple[str, str, np.ndarray]]  #: one against one: positive means the first
    members: dict[str, list[str]]
    within: dict[str, list[tuple[str, str, np.ndarray]]]

    @staticmethod
    def _vote(names: list[str], machines, margins: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index of the winner (votes, then summed margins, then order) and its confidence, per row."""
        votes, sums = np.zeros((len(margins), len(names))), np.zeros((len(margins), len(names)))
        for k, (a, b, _) in enumerate(machines):
            m = margins[:, k]
            i, j = names.index(a), names.index(b)
            votes[:, i] += m >= 0
            votes[:, j] += m < 0
            sums[:, i] += m
            sums[:, j] -= m
        won = np.argmax(votes + 0.5 * np.tanh(sums) / max(1, len(names)), axis=1)
        sure = np.ones(len(margins))
        for k, (a, b, _) in enumerate(machines):
            sign = np.where(won == names.index(a), 1.0, np.where(won == names.index(b), -1.0, np.nan))
            p = 1 / (1 + np.exp(-np.clip(2 * margins[:, k] * sign, -30, 30)))
            sure = np.where(np.isnan(sign), sure, np.fmin(sure, p))
        return won, sure

    def predict(self, x: np.ndarray) -> tuple[list[str], np.ndarray]:
        x = np.hstack([x, np.ones((len(x), 1))])
        names = list(self.members)
        fam, score = self._vote(names, self.families, np.stack([x @ w for _, _, w in self.families], 1) if self.families else np.zeros((len(x), 0)))
        out = np.empty(len(x), object)
        for f, name in enumerate(names):
            rows = np.nonzero(fam == f)[0]
            machines, langs = self.within[name], self.members[name]
            if len(rows):
                won, sure = self._vote(langs, machines, np.stack([x[rows] @ w for _, _, w in machines], 1) if machines else np.zeros((len(rows), 0)))
                out[rows] = np.array(langs, object)[won]
                score[rows] *= sure
        return out.tolist(), score


def _packed(x: np.ndarray) -> bytes:
    """The values above zero and their places; texts are short, so most are zero."""
    at = np.flatnonzero(x)
    return x[at].astype(np.float32).tobytes() + at.astype(np.uint16).tobytes()


def _unpacked(rows: list[bytes]) -> np.ndarray:
    x = np.zeros((len(rows), WIDTH), np.float32)
    for k, r in enumerate(rows):
        n = len(r) // 6
        x[k, np.frombuffer(r, np.uint16, n, 4 * n)] = np.frombuffer(r, np.float32, n)
    return x


def _families(langs: list[str]) -> dict[str, list[str]]:
    members: dict[str, list[str]] = {}
    for x in langs:
        members.setdefault(family_of(x), []).append(x)
    return members


def machines(data: dict[str, list[bytes]]) -> list[tuple[str, str, str, bytes]]:
    """``(level, a, b, weights)`` of all machines over packed features of each language, after one row for each language."""

    def machine(a: list[bytes], b: list[bytes]) -> bytes:
        return svm(_unpacked(a + b), np.concatenate([np.ones(len(a)), -np.ones(len(b))])).tobytes()

    members = _families(list(data))
    pool = {f: [r for x in m for r in data[x]] for f, m in members.items()}
    out = [("lang", x, "", b"") for x in data]
    out += [("family", f, g, machine(pool[f], pool[g])) for f, g in combinations(members, 2)]
    return out + [("within", a, b, machine(data[a], data[b])) for m in members.values() for a, b in combinations(m, 2)]


def fit(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", per_lang: int = 600, max_langs: int = 64) -> Model | None:
    """Model from at most ``per_lang`` labelled texts of each language (distinct ones of least hash), null and empty texts left out.

    That sample is the only bounded part: it is drawn over all rows, and its features (not its texts) go to one
    task, which trains; the driver gets the weights. Languages beyond the ``max_langs`` most frequent are not learnt.
    None if there is no labelled row.
    """
    usable = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull() & F.col(text_col).rlike(r"\p{L}"))
    keyed = usable.select(F.col(lang_col).cast("string").alias("lang"), F.xxhash64(text_col).alias("h"), F.col(text_col).cast("string").alias("text"))
    seen = {r["lang"]: r for r in keyed.groupBy("lang").agg(F.count("*").alias("n"), F.approx_count_distinct("h").alias("texts")).collect()}
    counts = {x: r["n"] for x, r in seen.items()}
    langs = sorted(sorted(counts, key=lambda x: (-counts[x], x))[:max_langs])
    if not langs:
        return None
    # a hash bound per language that some 1.7 times the sample of distinct texts passes, copies once, then its features
    bound = F.create_map(*[F.lit(y) for x in langs for y in (x, min(1.0, (1.7 * per_lang + 30) / max(1, seen[x]["texts"])))])
    chosen = keyed.where(F.col("lang").isin(langs)).where((F.pmod("h", F.lit(1 << 20)) / float(1 << 20)) < bound[F.col("lang")])
    chosen = chosen.groupBy("lang", "h").agg(F.first("text").alias("text"))

    def run(batches):
        for b in batches:
            out = [_packed(features(t)) for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out, pa.binary())], names=["lang", "h", "x"])

    def train(batches):
        by: dict[str, list[tuple]] = {x: [] for x in langs}
        for b in batches:
            for x, h, packed in zip(*(c.to_pylist() for c in b.columns)):
                by[x].append((h % (1 << 20), h, packed))
            by = {x: sorted(rows)[:per_lang] for x, rows in by.items()}
        found = machines({x: [r[2] for r in rows] for x, rows in by.items() if rows})
        yield pa.RecordBatch.from_pylist([dict(zip(("level", "a", "b", "w"), m)) for m in found], pa.schema([("level", pa.string()), ("a", pa.string()), ("b", pa.string()), ("w", pa.binary())]))

    # the sample meets in one task, so the driver gets nothing but weights
    rows = chosen.mapInArrow(run, "lang string, h bigint, x binary").repartition(1).mapInArrow(train, "level string, a string, b string, w binary").collect()
    weights = [(r["level"], r["a"], r["b"], np.frombuffer(bytes(r["w"]))) for r in rows]
    members = _families([a for level, a, _, _ in weights if level == "lang"])
    if not members:
        return None
    return Model(
        [(a, b, w) for level, a, b, w in weights if level == "family"],
        members,
        {f: [(a, b, w) for level, a, b, w in weights if level == "within" and a in m] for f, m in members.items()},
    )


def predict(docs: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``(id_col, *keep, lang_pred, score)``, one row per input row, from the text alone.

    ``lang_pred`` is a learnt language; ``und`` with score 0 where the text is null or has no letter, or where nothing was
    learnt. ``score`` (0 to 1) is the product of the least sure winning machines of both levels.
    """
    keep = list(keep or [])
    shared = docs.sparkSession.sparkContext.broadcast(model)
    cols = [id_col, *keep]
    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in cols) + ", lang_pred string, score double"

    def run(batches):
        m = shared.value
        for b in batches:
            langs, scores = ["und"] * b.num_rows, np.zeros(b.num_rows)
            some = b.column(b.num_columns - 1).to_pylist()
            texts = b.column(b.num_columns - 2)
            rows = [i for i, s in enumerate(some) if s] if m is not None else []
            for at in range(0, len(rows), 256):
                part = rows[at : at + 256]
                pred, sure = m.predict(np.stack([features(texts[i].as_py()) for i in part]))
                for i, p, s in zip(part, pred, sure):
                    langs[i], scores[i] = p, s
            yield pa.RecordBatch.from_arrays([*b.columns[: len(cols)], pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=[*cols, "lang_pred", "score"])

    letters = F.coalesce(F.col(text_col).rlike(r"\p{L}"), F.lit(False))
    return docs.select(*cols, F.col(text_col).cast("string").alias("_text"), letters.alias("_letters")).mapInArrow(run, schema)


def held_out(id_col: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 4 == 2, F.lit(False))
