"""A data source of made point sets: ``spark.read.format("pointset").option("side", 16)...``.

Kinds: ``grid``, the integer points of a cube (side, width), and ``cloud``, normal
points around a few centres (n, width, seed).  Rows follow from their numbers, so
partitions are replayable and need no input.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: Rows that a partition makes at once.
_CHUNK = 8192


class _Span(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class PointSetSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "pointset"

    def schema(self) -> str:
        return "point_id bigint, value array<double>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.kind = options.get("kind", "grid")
        self.width, self.side = int(options.get("width", 3)), int(options.get("side", 16))
        self.seed, self.parts = int(options.get("seed", 1)), int(options.get("partitions", 4))
        self.n = self.side**self.width if self.kind == "grid" else int(options.get("n", 1000))

    def partitions(self) -> list[_Span]:
        cuts = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [_Span(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if a < b]

    def read(self, span: _Span) -> Iterator[pa.RecordBatch]:
        for at in range(span.start, span.end, _CHUNK):
            ids = np.arange(at, min(at + _CHUNK, span.end), dtype=np.int64)
            if self.kind == "grid":
                values = np.stack([(ids // self.side**i) % self.side for i in range(self.width)], axis=1).astype(float)
            else:
                centres = np.random.default_rng(self.seed).normal(0, 3, (8, self.width))
                noise = np.stack([np.random.default_rng((self.seed, int(i))).normal(0, 0.5, self.width) for i in ids])
                values = centres[ids % 8] + noise
            offsets = pa.array(np.arange(0, values.size + 1, self.width, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.ListArray.from_arrays(offsets, pa.array(values.ravel()))], ["point_id", "value"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PointSetSource)
