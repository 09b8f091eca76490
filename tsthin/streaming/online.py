"""Streams of events: windows, watermarks, joins, and online thinning of closed chunks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..kernel.greedy import Rules, thin_array

KEPT = "series_id string, chunk long, pos long, value double"


class ChunkThinner(StatefulProcessor):
    """Buffers the points of a series by chunk; a chunk is thinned and emitted once later chunks have begun.

    Ends of chunks stay, so chunks join into one valid line; the bound holds in each chunk. State is what is not closed yet.
    """

    def __init__(self, rules: Rules, chunk: int):
        self.rules, self.chunk = rules, chunk

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.points = handle.getMapState("points", "pos long", "value double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        for b in rows:
            for p, v in zip(b["pos"].tolist(), b["value"].tolist()):
                self.points.updateValue((p,), (v,))
        held = sorted((k[0], v[0]) for k, v in self.points.iterator())
        last = held[-1][0] // self.chunk if held else 0
        closed: dict[int, list] = {}
        for p, v in held:
            if p // self.chunk < last:
                closed.setdefault(p // self.chunk, []).append((p, v))
        for c in sorted(closed):
            pos, x = np.array([q[0] for q in closed[c]]), np.array([q[1] for q in closed[c]])
            at = thin_array(x, self.rules)[0]
            for p in pos.tolist():
                self.points.removeKey((p,))
            yield pd.DataFrame({"series_id": key[0], "chunk": c, "pos": pos[at], "value": x[at]})

    def close(self) -> None:
        pass


def thin_online(stream: DataFrame, rules: Rules, chunk: int) -> DataFrame:
    """``(series_id, pos, value)`` stream to the kept points of closed chunks. Needs the RocksDB state store."""
    return stream.groupBy("series_id").transformWithStateInPandas(ChunkThinner(rules, chunk), KEPT, "Append", "None")


def thin_chunks(batch: DataFrame, rules: Rules, chunk: int) -> DataFrame:
    """The same on a table: chunks but the last of each series, each thinned by itself."""

    def one(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        at = thin_array(g["value"].to_numpy(float), rules)[0]
        return g.iloc[at][["series_id", "chunk", "pos", "value"]]

    s = batch.withColumn("chunk", F.floor(F.col("pos") / chunk).cast("long"))
    last = s.groupBy("series_id").agg(F.max("chunk").alias("last"))
    return s.join(last, "series_id").where("chunk < last").groupBy("series_id", "chunk").applyInPandas(one, KEPT)
