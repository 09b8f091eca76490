"""A Python data source that serves kept points as whole series: one partition per series, drawn in the reader."""

from __future__ import annotations

import base64
import json
import zlib

from pyspark.sql import DataFrame
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def pack(kept: DataFrame, most: int = 1_000_000) -> str:
    """Kept points of a few series as an option string; refused beyond ``most`` points, which belong in tables."""
    rows = kept.select("series_id", "pos", "value").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError("too many points for an option; write them as a table")
    by: dict[str, list] = {}
    for r in sorted(rows):
        by.setdefault(r["series_id"], []).append([r["pos"], r["value"]])
    return base64.b64encode(zlib.compress(json.dumps(by).encode())).decode()


class SeriesPartition(InputPartition):
    def __init__(self, series_id: str, points: list):
        super().__init__(series_id)
        self.series_id, self.points = series_id, points


class ThinnedReader(DataSourceReader):
    def __init__(self, options):
        self.by = json.loads(zlib.decompress(base64.b64decode(options["packed"])))

    def partitions(self):
        return [SeriesPartition(s, p) for s, p in self.by.items()]

    def read(self, partition):
        for (a, u), (b, v) in zip(partition.points, partition.points[1:]):
            for q in range(a, b):
                yield partition.series_id, q, float(u) if q == a else u + (v - u) * (q - a) / (b - a)
        if partition.points:
            a, u = partition.points[-1]
            yield partition.series_id, a, float(u)


class ThinnedSource(DataSource):
    @classmethod
    def name(cls):
        return "thinned"

    def schema(self):
        return "series_id string, pos bigint, value double"

    def reader(self, schema):
        return ThinnedReader(self.options)
