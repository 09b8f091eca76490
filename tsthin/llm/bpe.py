"""Byte-level BPE encoding and decoding through a table of distinct words.

The words of all texts are counted in Spark; every word among the most frequent ones (a table of bounded size, so
that it can be broadcast whatever the corpus) is encoded once, and ids are joined back by position. Words outside
that table, each rare, are encoded once in every task that meets them, in a table of the task that is bounded too. Decoding joins ids
to vocabulary pieces. Texts never cross the network.
"""

from __future__ import annotations

import hashlib
import json
import re
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .support import cut

#: How byte-level BPE cuts text into words (fixed values, the published pattern of this kind of vocabulary).
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: The same cut where all characters are ASCII or Latin letters up to U+017F: classes spelt out, common cases first.
LATIN = "A-Za-zÀ-ÖØ-öø-ſ"
LATIN_ONLY = re.compile(f"[\\x00-\\x7f{LATIN}]*")
LATIN_WORDS = re.compile(rf" ?[{LATIN}]+|'(?:[stmd]|re|ve|ll)| ?[0-9]+| ?[^\s{LATIN}0-9]+|\s+(?!\S)|\s+", re.ASCII)
TABLE_WORDS = 1 << 17  #: most words of the broadcast table
TABLE_CHARS = 64  #: longest word of the broadcast table
TASK_WORDS = 1 << 17  #: most words of a task's own table; it starts anew beyond


class Coder:
    """Vocabulary of a tokenizer file, in one process."""

    def __init__(self, text: str):
        import regex

        spec = json.loads(text)
        added = sorted((x["content"] for x in spec.get("added_tokens", [])), key=len, reverse=True)
        self.special = {x["content"]: x["id"] for x in spec.get("added_tokens", [])}
        self.marks = regex.compile("|".join(map(regex.escape, added))) if added else None
        self.words = regex.compile(WORDS)
        visible = [*range(33, 127), *range(161, 173), *range(174, 256)]
        as_byte = {chr(b): b for b in visible} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(visible))}
        self.pieces: dict[int, bytes] = {i: bytes(as_byte[c] for c in piece) for piece, i in spec["model"]["vocab"].items() if piece not in self.special}
        ranks = {p: i for i, p in self.pieces.items()}
        self.pieces |= {i: piece.encode() for piece, i in self.special.items()}
        # where ids rank the merges, as in files of this kind, a merge loop by ranks gives the same ids, far cheaper for single words
        merges = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        first = min((spec["model"]["vocab"]["".join(m)] for m in merges), default=0)
        self.core = self.tokenizer = None
        if not spec["model"].get("ignore_merges") and all(spec["model"]["vocab"]["".join(m)] == first + i for i, m in enumerate(merges)) and all(bytes([b]) in ranks for b in range(256)):
            import tiktoken

            self.core = tiktoken.Encoding("words", pat_str=r"(?s).+", mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece
        else:
            from tokenizers import Tokenizer

            self.tokenizer = Tokenizer.from_str(text)
            self.tokenizer.no_truncation()
            self.tokenizer.no_padding()

    def split(self, text: str) -> list[str]:
        """Words in order; strings of added tokens are words of their own."""
        if self.marks is None or not any(s in text for s in self.special):
            return (LATIN_WORDS if LATIN_ONLY.fullmatch(text) else self.words).findall(text)
        out, at = [], 0
        for m in self.marks.finditer(text):
            out += [*self.words.findall(text[at : m.start()]), m[0]]
            at = m.end()
        return out + self.words.findall(text[at:])

    def encode(self, words: list[str]) -> list[list[int]]:
        """Ids of each word; a word is encoded by itself, as the cut makes it."""
        if self.core is not None:
            return [self.core(w.encode()) for w in words]
        return [x.ids for x in self.tokenizer.encode_batch(words, add_special_tokens=False)]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.pieces.__getitem__, ids))


class Table(dict):
    """Words to (ids as text, decoded bytes, ids as packed 32-bit numbers). Words outside the given table are encoded when first met; ``trim`` bounds them."""

    def __init__(self, c: Coder, known):
        self.coder = c
        super().__init__((w, self.entry(x)) for w, x in known)
        self.update((s, self.entry([i])) for s, i in c.special.items())
        self.floor = len(self)

    def entry(self, ids):
        return ",".join(map(str, ids)), self.coder.decode(ids), np.array(ids, np.int32).tobytes()

    def __missing__(self, word):
        self[word] = found = self.entry(self.coder.encode([word])[0])
        return found

    def trim(self):
        if len(self) - self.floor > TASK_WORDS:
            for w in list(self)[self.floor :]:
                del self[w]


_tables: dict[str, Table] = {}


def task_table(c: Coder, known, key: str) -> Table:
    """The process's table for one call of the encoder: workers are used again, and their tables with them."""
    if key not in _tables:
        _tables.clear()
        _tables[key] = Table(c, zip(known.column(0).to_pylist(), known.column(1).to_pylist()))
    return _tables[key]


_coders: dict[str, Coder] = {}


def coder(text: str) -> Coder:
    key = hashlib.sha256(text.encode()).hexdigest()
    if key not in _coders:
        _coders.clear()
        _coders[key] = Coder(text)
    return _coders[key]


def read_tokenizer(path: str) -> str:
    with open(path, encoding="utf-8") as f:
        return f.read()


def word_table(docs: DataFrame, tokenizer: str, text_col: str = "text", most: int = TABLE_WORDS) -> DataFrame:
    """``(word, n, ids)``: the most frequent words of all texts, at most ``most`` of them, each encoded once.

    Counts are over all rows. The cut is at a count, found from a histogram of counts (some hundred classes), so no
    task sorts the vocabulary. Words above ``TABLE_CHARS`` characters are left to the tasks that meet them.
    """
    shared = docs.sparkSession.sparkContext.broadcast(tokenizer)

    def count(batches):
        from collections import Counter

        c, held = coder(shared.value), Counter()

        def out():
            kept = [(w, n) for w, n in held.items() if len(w) <= TABLE_CHARS]
            held.clear()
            for at in range(0, len(kept), 50_000):
                w, n = zip(*kept[at : at + 50_000])
                yield pa.RecordBatch.from_arrays([pa.array(w, pa.string()), pa.array(n, pa.int64())], names=["word", "n"])

        for b in batches:
            for t in b.column(0).to_pylist():
                if t:
                    held.update(c.split(t))
                if len(held) > TASK_WORDS:
                    yield from out()
        yield from out()

    def encode(batches):
        c = coder(shared.value)
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(c.encode(b.column(0).to_pylist()), pa.list_(pa.int32()))], names=["word", "n", "ids"])

    counted = docs.select(F.col(text_col).cast("string").alias("t")).mapInArrow(count, "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n"))
    counted = cut(counted.withColumn("class", F.floor(F.log2("n") * 16).cast("int")))
    least, taken = 1 << 30, 0
    for r in sorted(counted.groupBy("class").agg(F.count("*").alias("words")).collect(), key=lambda r: -r["class"]):
        taken += r["words"]
        if taken > most:
            break
        least = r["class"]
    return counted.where(F.col("class") >= least).select("word", "n").mapInArrow(encode, "word string, n bigint, ids array<int>")


def encode_documents(docs: DataFrame, tokenizer: str, words: DataFrame, id_col: str = "doc_id", text_col: str = "text", ids: bool = True, decoded: bool = True) -> DataFrame:
    """``(id_col, n_tokens, ids, decoded, ids_sha256, decoded_sha256)``, one row per input row, in place.

    ``words``: a table as ``word_table`` gives it (bounded, hence collected and broadcast). Null texts are empty.
    Without ``ids`` or ``decoded`` these columns are null, which spares memory where digests do.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast((tokenizer, words.select("word", "ids").toArrow().combine_chunks(), uuid.uuid4().hex))
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        text, known, key = shared.value
        c = coder(text)

        table = task_table(c, known, key)
        for b in batches:
            counts, numbers, texts, digests, proofs = [], [], [], [], []
            for t in b.column(1):
                t = t.as_py()
                listed, pieces, packed = zip(*map(table.__getitem__, c.split(t))) if t else ((), (), ())
                table.trim()
                listed, out = ",".join(listed), b"".join(pieces).decode("utf-8", "replace")
                counts.append(listed.count(",") + 1 if listed else 0)
                digests.append(hashlib.sha256(listed.encode()).hexdigest())
                proofs.append(hashlib.sha256(out.encode()).hexdigest())
                if ids:
                    numbers.append(b"".join(packed))
                if decoded:
                    texts.append(out)
            none = [None] * b.num_rows
            listed = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(counts)), pa.int32()), pa.array(np.frombuffer(b"".join(numbers), np.int32))) if ids else pa.array(none, pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(counts, pa.int64()), listed, pa.array(texts if decoded else none, pa.string()), pa.array(digests, pa.string()), pa.array(proofs, pa.string())],
                names=[id_col, "n_tokens", "ids", "decoded", "ids_sha256", "decoded_sha256"],
            )

    schema = f"`{id_col}` {kind}, n_tokens bigint, ids array<int>, decoded string, ids_sha256 string, decoded_sha256 string"
    return docs.select(id_col, F.col(text_col).cast("string").alias("t")).mapInArrow(run, schema)


def encode_corpus(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", ids: bool = True, decoded: bool = True) -> DataFrame:
    return encode_documents(docs, tokenizer, word_table(docs, tokenizer, text_col), id_col, text_col, ids, decoded)


def decode_documents(encoded: DataFrame, tokenizer: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """``(id_col, decoded)``: ids to text through the table of pieces; invalid UTF-8 is replaced; null ids give null."""
    shared = encoded.sparkSession.sparkContext.broadcast(tokenizer)
    kind = encoded.schema[id_col].dataType.simpleString()

    def run(batches):
        c = coder(shared.value)
        for b in batches:
            out = [None if x is None else c.decode(x).decode("utf-8", "replace") for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.string())], names=[id_col, "decoded"])

    return encoded.select(id_col, ids_col).mapInArrow(run, f"`{id_col}` {kind}, decoded string")
