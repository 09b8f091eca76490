"""Chat formatting by event-sourced reconstruction.

A conversation is a log of events ordered by (turn, seq). Folding gives its final messages; rendering gives one
segment of formatted text per message, with the part that a loss should see; the formatted conversation is the
concatenation of its segments in order. Everything streams over rows sorted by conversation, so a conversation of any
length needs the memory of one message only.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

# Fixed values of the template. Inside texts and roles a backslash comes before every backslash and control string.
HEAD, COLON, TAIL, MARK = "### ", ":\n", "\n</turn>\n", "\\"
CONTROL = re.compile(r"\\|###|</turn>")
ESCAPED = re.compile(r"\\(\\|###|</turn>)")
ESCAPED_ROLE = re.compile(r"\\(\\|###|</turn>|n)")


def escape(text: str) -> str:
    return CONTROL.sub(lambda m: MARK + m[0], text)


def unescape(text: str) -> str:
    return ESCAPED.sub(lambda m: m[1], text)


def escape_role(role: str) -> str:
    """As ``escape``; line ends, which end a role, are written as a backslash and n."""
    return escape(role).replace("\n", "\\n")


def unescape_role(role: str) -> str:
    return ESCAPED_ROLE.sub(lambda m: "\n" if m[1] == "n" else m[1], role)


def render(role: str, text: str) -> tuple[str, int, int]:
    """The segment of one message, and where its text lies in it."""
    head, body = HEAD + escape_role(role) + COLON, escape(text)
    return head + body + TAIL, len(head), len(head) + len(body)


def parse(formatted: str) -> Iterator[tuple[str, str, int, int]]:
    """``(role, text, start, end)`` of each message of a formatted text, from the text alone."""
    at = 0
    while at < len(formatted):
        if not formatted.startswith(HEAD, at):
            raise ValueError(f"no turn starts at {at}")
        colon = formatted.index(COLON, at)
        start = colon + len(COLON)
        end = formatted.index(TAIL, start)
        yield unescape_role(formatted[at + len(HEAD) : colon]), unescape(formatted[start:end]), start, end
        at = end + len(TAIL)


#: of the event log; kinds: message, delta, edit, regenerate, delete
EVENTS = "turn bigint, seq bigint, kind string, role string, text string"


def as_log(messages: DataFrame, conv_col: str = "conv_id") -> DataFrame:
    """``(conv_col, EVENTS)``: final messages ``(conv_col, turn, role, text)`` as a log that ``fold`` takes back to them.

    Assistants' messages begin with their text's first half, are regenerated, and stream in as two deltas; other messages
    begin as a draft of their length and are edited. Order within a conversation is by turn, role, text; rows that
    repeat are messages each. Null texts and roles stay null until ``fold`` makes them empty.
    """
    half = F.floor(F.length("text") / 2).cast("int")
    event = lambda step, kind, text: F.struct((4 * F.col("at") + step).alias("seq"), F.lit(kind).alias("kind"), text.alias("text"))
    head, tail = F.substring("text", F.lit(1), half), F.substring("text", half + 1, F.length("text") - half)
    streamed = F.array(event(0, "message", head), event(1, "regenerate", F.lit(None).cast("string")), event(2, "delta", head), event(3, "delta", tail))
    edited = F.array(event(0, "message", F.translate("text", "aeiou", "xxxxx")), event(1, "edit", F.col("text")))
    order = Window.partitionBy(conv_col).orderBy("turn", "role", "text")
    rows = messages.select(conv_col, F.col("turn").cast("long").alias("turn"), "role", "text").withColumn("at", F.row_number().over(order).cast("long"))
    rows = rows.select(conv_col, "turn", "role", F.explode(F.when(F.col("role") == "assistant", streamed).otherwise(edited)).alias("e"))
    return rows.select(conv_col, "turn", "e.seq", "e.kind", "role", "e.text")


def fold(events: DataFrame, conv_col: str = "conv_id") -> DataFrame:
    """Final messages ``(conv_col, turn, role, text)`` of an event log, sorted by conversation and turn within partitions.

    Events of a turn apply by ``seq``: ``message`` starts a message (a turn may hold several), ``delta`` appends to
    the turn's last message (starting one if there is none), ``edit`` replaces its text, ``regenerate`` empties it and
    takes back what later turns were logged before it, ``delete`` removes it; other kinds and null kinds count as
    ``message``. Null text is empty, a null role is empty (for deltas and edits: as before). Ties in (turn, seq) go by
    kind, role, text; null turns come first. Rows with a null conversation form one conversation. Messages that end
    empty stay, as empty messages.
    """
    kind = events.schema[conv_col].dataType.simpleString()
    order = [F.col(conv_col), F.col("turn"), F.col("seq"), F.col("kind"), F.col("role"), F.col("text")]
    log = events.select(conv_col, F.col("turn").cast("long"), F.col("seq").cast("long"), F.col("kind").cast("string"), F.col("role").cast("string"), F.col("text").cast("string"))
    log = log.repartition(F.col(conv_col)).sortWithinPartitions(*order)

    def run(batches):
        conv = turn = object()
        open_: list[list] = []  # messages of the current turn: role, pieces
        cut = turn_cut = None  # seq of the last regeneration in earlier turns, and including this one

        def close(out):
            out.extend((conv, turn, m[0], "".join(m[1])) for m in open_)
            open_.clear()

        for b in batches:
            out: list[tuple] = []
            for c, t, seq, k, role, text in zip(*(col.to_pylist() for col in b.columns)):
                if c != conv or t != turn:
                    close(out)
                    cut = turn_cut if c == conv else None
                    if c != conv:
                        turn_cut = None
                    conv, turn = c, t
                if cut is not None and seq is not None and seq < cut:
                    continue
                if k == "delta":
                    if not open_:
                        open_.append([role or "", []])
                    open_[-1][0] = role if role is not None else open_[-1][0]
                    open_[-1][1].append(text or "")
                elif k == "edit" and open_:
                    open_[-1] = [role if role is not None else open_[-1][0], [text or ""]]
                elif k == "regenerate":
                    if open_:
                        open_[-1][1] = []
                    turn_cut = seq if turn_cut is None else max(turn_cut, seq or 0)
                elif k == "delete":
                    if open_:
                        open_.pop()
                else:
                    open_.append([role or "", [text or ""]])
            if out:
                yield _batch(out)
        out = []
        close(out)
        if out:
            yield _batch(out)

    def _batch(out):
        cols = list(zip(*out))
        return pa.RecordBatch.from_arrays([pa.array(cols[0], arrow), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.string()), pa.array(cols[3], pa.string())], names=[conv_col, "turn", "role", "text"])

    from pyspark.sql.pandas.types import to_arrow_type

    arrow = to_arrow_type(events.schema[conv_col].dataType)
    return log.mapInArrow(run, f"`{conv_col}` {kind}, turn bigint, role string, text string")


def format_messages(messages: DataFrame, conv_col: str = "conv_id", learn: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """``(conv_col, turn, segment, loss_start, loss_end)``: rendered messages, in the order of the input rows.

    The loss mask covers ``segment[loss_start:loss_end]`` (code points): the texts of the roles in ``learn``, without
    markers; it is empty (both zero) for others.
    """
    kind = messages.schema[conv_col].dataType.simpleString()

    def run(batches):
        for b in batches:
            seg, lo, hi = [], [], []
            for role, text in zip(b.column(2).to_pylist(), b.column(3).to_pylist()):
                s, start, end = render(role, text)
                seg.append(s)
                lo.append(start if role in learn else 0)
                hi.append(end if role in learn else 0)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(seg, pa.string()), pa.array(lo, pa.int64()), pa.array(hi, pa.int64())], names=[conv_col, "turn", "segment", "loss_start", "loss_end"])

    return messages.select(conv_col, "turn", "role", "text").mapInArrow(run, f"`{conv_col}` {kind}, turn bigint, segment string, loss_start bigint, loss_end bigint")


def digest(segments: DataFrame, conv_col: str = "conv_id") -> DataFrame:
    """Per conversation, read back from the rendered segments alone: number of turns, digests and sizes.

    ``segments`` must come, per conversation, in order and in one partition, as ``format_messages(fold(...))`` gives them.
    """
    from pyspark.sql.pandas.types import to_arrow_type

    field = segments.schema[conv_col].dataType
    arrow = to_arrow_type(field)
    names = [conv_col, "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]

    def run(batches):
        conv, state = object(), None

        def done():
            return (conv, state[0], state[1].hexdigest(), state[2], state[3].hexdigest(), state[4])

        def batch(out):
            cols = list(zip(*out))
            kinds = [arrow, pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

        for b in batches:
            out = []
            for c, segment, lo, hi in zip(*(b.column(i).to_pylist() for i in (0, 2, 3, 4))):
                if state is None or c != conv:
                    if state is not None:
                        out.append(done())
                    conv, state = c, [0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                for role, text, _, _ in parse(segment):
                    state[0] += 1
                    state[1].update(f"{role}\n{text}\n".encode())
                learnt = unescape(segment[lo:hi])
                state[2] += len(learnt)
                state[3].update(learnt.encode())
                state[4] += len(segment)
            if out:
                yield batch(out)
        if state is not None:
            yield batch([done()])

    return segments.select(conv_col, "turn", "segment", "loss_start", "loss_end").mapInArrow(
        run, f"`{conv_col}` {field.simpleString()}, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint"
    )
