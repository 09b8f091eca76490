"""Benchmark decontamination by template canonicalisation.

Numbers, names and units become typed placeholders; windows of five template tokens of documents and benchmark items
meet in a hash join; a name is a word with one leading capital inside a sentence; the values that filled the placeholders must map consistently from item to document. This finds
copies and questions asked again with other parameters.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .support import cut

WINDOW = 5
LITERALS = 3  #: least number of ordinary words in a window that counts
TOKENS = re.compile(r"[^\W\d_]+|\d+(?:[.,]\d+)*|[.!?:;\n]")
#: The same where all characters are ASCII or Latin letters up to U+017F.
LATIN = "A-Za-zÀ-ÖØ-öø-ſ"
LATIN_ONLY = re.compile(f"[\\x00-\\x7f{LATIN}]*")
LATIN_TOKENS = re.compile(rf"[{LATIN}]+|[0-9]+(?:[.,][0-9]+)*|[.!?:;\n]")
#: Units, fixed values; they count as such after a number only.
UNITS = (
    "mm cm dm m km in inch inches ft foot feet yd yard yards mi mile miles mg g kg t ton tons lb lbs pound pounds oz ounce ounces "
    "ml cl dl l liter liters litre litres gallon gallons ms s sec second seconds min minute minutes h hr hrs hour hours day days week weeks "
    "month months year years c f k degree degrees percent dollar dollars euro euros cent cents usd eur w kw v a hz kb mb gb tb"
).split()
WORD, CAPITAL, NUMBER, BREAK = range(4)
_TYPES = {t: np.uint64(xxhash.xxh64_intdigest(f"<{t}>")) for t in ("num", "name", "unit")}
_FACTOR = 0x9E3779B97F4A7C15
_RAW = [xxhash.xxh64_intdigest(f"raw {k}") for k in range(WINDOW + 1)]
_POWERS = np.array([pow(_FACTOR, k, 1 << 64) for k in range(WINDOW)], dtype=np.uint64)


class Ids(dict):
    """Tokens to their numbers; a new token gets the next."""

    def __init__(self, new):
        self.new = new

    def __missing__(self, token):
        self[token] = at = len(self)
        self.new(token)
        return at


class Canon:
    """Texts to template codes. Token attributes are kept in a table of bounded size."""

    def __init__(self, most: int = 1 << 19):
        self.most, self.units = most, frozenset(UNITS)
        self.clear()

    def clear(self):
        self.ids, self.new = Ids(self._new), []
        self.codes, self.kinds, self.is_unit = np.zeros(1024, np.uint64), np.zeros(1024, np.int8), np.zeros(1024, bool)

    def _new(self, token: str):
        low = token.lower()
        kind = BREAK if token in ".!?:;\n" else NUMBER if token[0].isdigit() else CAPITAL if len(token) > 1 and token[0] != low[0] and token[1:] == low[1:] else WORD
        self.new.append((xxhash.xxh64_intdigest(low.encode()), kind, low in self.units))

    def _settle(self):
        """Move attributes of new tokens to the arrays, which double when they are full."""
        lo, hi = len(self.ids) - len(self.new), len(self.ids)
        while hi > len(self.codes):
            self.codes, self.kinds, self.is_unit = (np.concatenate([a, np.zeros_like(a)]) for a in (self.codes, self.kinds, self.is_unit))
        code, kind, unit = zip(*self.new)
        self.codes[lo:hi], self.kinds[lo:hi], self.is_unit[lo:hi] = np.array(code, np.uint64), kind, unit
        self.new = []

    def __call__(self, text: str):
        """``(tokens, codes, placeholder, raw, begins, ends)``, without breaks.

        ``codes`` are those of the template, ``raw`` those of the tokens themselves; ``placeholder`` is 0 or its type
        (1 num, 2 name, 3 unit); the last two tell what stands after and before a break or the end of the text.
        """
        tokens = (LATIN_TOKENS if LATIN_ONLY.fullmatch(text) else TOKENS).findall(text)
        if len(self.ids) > self.most:
            self.clear()
        ids = np.fromiter(map(self.ids.__getitem__, tokens), np.int64, len(tokens))
        if self.new:
            self._settle()
        if not len(ids):
            return [], np.zeros(0, np.uint64), np.zeros(0, np.int8), np.zeros(0, np.uint64), np.zeros(0, bool), np.zeros(0, bool)
        raw, kind, unit = self.codes[ids], self.kinds[ids], self.is_unit[ids]
        before = np.concatenate([[BREAK], kind[:-1]])
        slot = np.zeros(len(ids), np.int8)
        slot[kind == NUMBER] = 1
        slot[(kind == CAPITAL) & (before != BREAK)] = 2
        slot[unit & (before == NUMBER)] = 3
        code = raw.copy()
        for t, name in ((1, "num"), (2, "name"), (3, "unit")):
            code[slot == t] = _TYPES[name]
        real = kind != BREAK
        keep = np.nonzero(real)[0]
        after = np.concatenate([kind[1:], [BREAK]])
        return [tokens[i] for i in keep], code[real], slot[real], raw[real], before[real] == BREAK, after[real] == BREAK


def _hashes(codes: np.ndarray, size: int, salt: int = 0) -> np.ndarray:
    n = max(0, len(codes) - size + 1)
    h = np.full(n, salt, np.uint64)
    for k in range(size):
        h += codes[k : k + n] * _POWERS[k]
    h ^= h >> np.uint64(29)
    return h * np.uint64(0xBF58476D1CE4E5B9)


def windows(codes: np.ndarray, slots: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each template window and its number of ordinary words."""
    h = _hashes(codes, WINDOW)
    literal = np.zeros(len(h), np.int64)
    for k in range(WINDOW):
        literal += slots[k : k + len(h)] == 0
    return h, literal


def raw_windows(raw: np.ndarray) -> np.ndarray:
    """Hash of each window of the tokens themselves; another than that of the same template window."""
    return _hashes(raw, WINDOW, _RAW[WINDOW])


def sentences(raw: np.ndarray, begins: np.ndarray, ends: np.ndarray, sizes):
    """``(at, hash)`` of runs of these sizes that stand between breaks."""
    for size in sizes:
        at = np.nonzero(begins[: max(0, len(raw) - size + 1)] & ends[size - 1 :])[0]
        if len(at):
            yield at, _hashes(raw, size, _RAW[size])[at]


def _slots(tokens, slots, at) -> list[str]:
    return [f"{slots[i]}:{tokens[i].lower()}" for i in range(at, at + WINDOW) if slots[i]]


#: Kinds of windows: of the template with enough ordinary words, with one at least, of the tokens themselves; a short
#: item's kind is SHORT + its number of tokens.
WORDY, LOOSE, RAW, SHORT = 0, 1, 2, 10


def _of_item(tokens, codes, slots, raw, least):
    """``(at, hash, kind)`` of an item's windows.

    Where the windows of enough ordinary words reach less than ``least`` of the tokens, those of one or two and the
    windows of the tokens themselves count too; an item shorter than a window is one run. Numbers alone give nothing.
    """
    words = any(not t[0].isdigit() for t in tokens)
    if len(tokens) < WINDOW:
        return [(np.zeros(1, np.int64), _hashes(raw, len(raw), _RAW[len(raw)]), SHORT + len(raw))] if words else []
    h, literal = windows(codes, slots)
    at = np.nonzero(literal >= LITERALS)[0]
    reach = np.zeros(len(tokens), bool)
    for k in range(WINDOW):
        reach[at + k] = True
    if reach.sum() >= least * len(tokens) or not words:
        return [(at, h[at], WORDY)]
    at = np.nonzero(literal)[0]
    return [(at, h[at], LOOSE), (np.arange(len(h)), raw_windows(raw), RAW)]


def _of_text(codes, slots, raw, begins, ends, kinds):
    """``(at, hash, kind)`` of all windows of a text that an item's can be equal to; ``kinds`` are those of the items."""
    if WORDY in kinds or LOOSE in kinds:
        h, literal = windows(codes, slots)
        at = np.nonzero(literal >= (1 if LOOSE in kinds else LITERALS))[0]
        yield at, h[at], LOOSE
    if RAW in kinds:
        h = raw_windows(raw)
        yield np.arange(len(h)), h, RAW
    for at, h in sentences(raw, begins, ends, sorted(k - SHORT for k in kinds if k > SHORT)):
        yield at, h, SHORT


def template_windows(docs: DataFrame, id_col: str, text_col: str, wanted: np.ndarray | None = None, least: float | None = None, kinds: frozenset = frozenset()) -> DataFrame:
    """``(id_col, h, at, slots, n, row, kind)``: windows of each text; with ``wanted`` (sorted hashes) only those it holds.

    With ``least`` the texts are items; else only windows of the given kinds, those that items have, are made. ``slots`` are the values of placeholders, none in windows of the tokens
    themselves; ``row`` tells rows of the same id apart.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(wanted)
    id_type = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        canon, want = Canon(), shared.value
        if want is not None:  # most windows fall out by their first bits
            some = np.zeros(1 << 16, bool)
            some[want >> np.uint64(48)] = True
        for b in batches:
            who, hs, ats, sl, ns, rows, of = [], [], [], [], [], [], []
            for row, t in enumerate(b.column(1).to_pylist()):
                if not t:
                    continue
                tokens, codes, slots, raw, begins, ends = canon(t)
                if not tokens:
                    continue
                name = None
                for at, h, kind in _of_text(codes, slots, raw, begins, ends, kinds) if least is None else _of_item(tokens, codes, slots, raw, least):
                    if want is not None and len(h):
                        hits = np.nonzero(some[h >> np.uint64(48)])[0]
                        i = np.minimum(np.searchsorted(want, h[hits]), len(want) - 1)
                        hits = hits[want[i] == h[hits]]
                        at, h = at[hits], h[hits]
                    if not len(h):
                        continue
                    if name is None:
                        name = xxhash.xxh64_intdigest(t.encode("utf-8", "replace")) >> 1
                    who += [row] * len(h)
                    hs.append(h)
                    ats.append(at)
                    sl += [_slots(tokens, slots, int(x)) if kind <= LOOSE else [] for x in at]
                    of += [kind] * len(h)
                    ns += [len(tokens)] * len(h)
                    rows += [name] * len(h)
            hs, ats = (np.concatenate(x) if x else np.zeros(0, np.uint64) for x in (hs, ats))
            yield pa.RecordBatch.from_arrays(
                [b.column(0).take(pa.array(who, pa.int64())), pa.array(hs.view(np.int64)), pa.array(ats.astype(np.int32)), pa.array(sl, pa.list_(pa.string())), pa.array(ns, pa.int32()), pa.array(rows, pa.int64()), pa.array(of, pa.int32())],
                names=[id_col, "h", "at", "slots", "n", "row", "kind"],
            )

    return docs.select(id_col, F.col(text_col).cast("string").alias("_t")).mapInArrow(run, f"`{id_col}` {id_type}, h bigint, at int, slots array<string>, n int, row bigint, kind int")


def contaminated(
    docs: DataFrame,
    benchmark: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    least: float = 0.8,
    broadcast_hashes: int = 4_000_000,
    occurrences: bool = False,
) -> DataFrame:
    """Pairs ``(id_col, item_col, coverage, copied, consistency, reworded)`` of documents and the items they hold.

    ``coverage``: share of the item's tokens that lie in a window met in the document; ``copied``: the same, of windows
    whose placeholders hold the same values; ``consistency``: placeholder values of the item over distinct
    (item value, document value) bindings, 1 without placeholders. A pair is given if ``copied`` is at least ``least``,
    or coverage and consistency are; ``reworded`` tells that only the latter holds.
    With ``occurrences`` a pair is given too if one occurrence of the item passes by itself, whatever else the document
    holds (an exercise sheet asks one question many times): windows of one row of the document that begin the item at the
    same token, or within half an item's length. The figures are then those of the best occurrence.
    Items rich in placeholders are met by all their windows, of the template and of the tokens themselves; items of
    fewer than five tokens where the same tokens stand between breaks. Null and empty texts, items of numbers alone, and
    null ids give no pair. Repeated rows of an id
    count together. Item hashes are broadcast as a filter if there are at most ``broadcast_hashes`` of them; beyond
    that all windows go through the join itself.
    """
    items = cut(template_windows(benchmark.where(F.col(item_col).isNotNull()).select(F.col(item_col).alias("_item"), F.col(item_text_col).alias("_it")), "_item", "_it", least=least))
    hashes = items.select("h").distinct()
    kinds = frozenset(r["kind"] for r in items.select("kind").distinct().collect())
    wanted = None
    if hashes.limit(broadcast_hashes + 1).count() <= broadcast_hashes:
        wanted = np.sort(np.asarray(hashes.toArrow().column(0).to_numpy(), dtype=np.int64).view(np.uint64))
        if not len(wanted):
            wanted = np.array([0], dtype=np.uint64)
    found = template_windows(docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("_doc"), F.col(text_col).alias("_dt")), "_doc", "_dt", wanted, kinds=kinds)
    met = (
        found.select("_doc", "h", F.col("slots").alias("d_slots"), F.col("at").alias("d_at"), "row")
        .join(items.select("h", "_item", F.col("at").alias("i_at"), F.col("slots").alias("i_slots"), F.col("n").alias("i_n")), "h")
        .withColumn("start", F.col("d_at") - F.col("i_at"))
    )
    group = lambda kind, row, at: F.struct(F.lit(kind).alias("kind"), row.cast("long").alias("row"), at.cast("long").alias("at"))
    groups, cell = [group(0, F.lit(0), F.lit(0))], F.greatest(F.lit(2), F.col("i_n"))
    if occurrences:  # two grids, so that starts within half a cell share one in either
        grids = [F.col("start"), F.floor(F.col("start") / cell), F.floor(F.col("start") / cell + 0.5)]
        groups += [group(k, F.col("row"), g) for k, g in enumerate(grids, 1)]
    met = cut(met.select("_doc", "_item", F.explode(F.array(*groups)).alias("g"), "i_at", "i_n", "i_slots", "d_slots").distinct())
    tokens = lambda at: F.size(F.array_distinct(F.flatten(F.transform(at, lambda p: F.sequence(p, p + WINDOW - 1)))))
    same = F.when(F.col("i_slots") == F.col("d_slots"), F.col("i_at"))
    of = ["_doc", "_item", "g"]
    cover = met.groupBy(*of).agg(F.max("i_n").alias("n"), F.collect_set("i_at").alias("a"), F.collect_set(same).alias("c"))
    cover = cover.select(*of, (F.least(tokens(F.col("a")), "n") / F.col("n")).alias("coverage"), (F.least(tokens(F.col("c")), "n") / F.col("n")).alias("copied"))
    bound = met.select(*of, F.explode(F.arrays_zip("i_slots", "d_slots")).alias("s")).groupBy(*of, "s.i_slots", "s.d_slots").agg(F.lit(1).alias("one"))
    bound = bound.groupBy(*of, "i_slots").agg(F.count("*").alias("k")).groupBy(*of).agg((F.count("*") / F.sum("k")).alias("fit"))
    out = cover.where(F.col("coverage") >= least).join(bound, of, "left").withColumn("consistency", F.coalesce("fit", F.lit(1.0)))
    out = out.where((F.col("copied") >= least) | (F.col("consistency") >= least))
    if occurrences:  # the document as a whole where that passes, else its best occurrence
        best = F.max_by(F.struct("coverage", "copied", "consistency"), F.struct(F.col("g.kind") == 0, "copied", "coverage", "consistency"))
        out = out.groupBy("_doc", "_item").agg(best.alias("b")).select("_doc", "_item", "b.*")
    return out.select(F.col("_doc").alias(id_col), F.col("_item").alias(item_col), "coverage", "copied", "consistency", (F.col("copied") < least).alias("reworded"))
