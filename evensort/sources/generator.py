"""A Python data source that makes the input sequences at any size, in parallel."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.keys import MIX

BATCH = 1 << 16


def mix32(x: np.ndarray) -> np.ndarray:
    a, c, b, d = (np.uint64(v) for v in MIX)
    word = np.uint64((1 << 32) - 1)
    h = (x.astype(np.uint64) * a + c) & word
    h = ((h ^ (h >> np.uint64(16))) * b) & word
    h = ((h ^ (h >> np.uint64(15))) * d) & word
    return (h ^ (h >> np.uint64(16))).astype(np.int64)


def keys(kind: str, pos: np.ndarray) -> np.ndarray:
    if kind == "uniform_int":
        return mix32(pos)
    if kind == "uniform_float":
        return mix32(pos) / float(1 << 32)
    if kind == "dup3":
        return mix32(pos) % 3
    if kind == "sorted":
        return pos
    raise ValueError(f"unknown sequence {kind}")


class Span(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class SequenceReader(DataSourceReader):
    def __init__(self, options):
        self.kind = options.get("kind", "uniform_int")
        self.n = int(options.get("n", "1000"))
        self.parts = int(options.get("parts", "8"))

    def partitions(self):
        cuts = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [Span(a, b) for a, b in zip(cuts, cuts[1:])]

    def read(self, span):
        for at in range(span.start, span.end, BATCH):
            pos = np.arange(at, min(at + BATCH, span.end), dtype=np.int64)
            made = keys(self.kind, pos)
            yield pa.RecordBatch.from_arrays([pa.array(pos), pa.array(made)], names=["pos", "key"])


class SequenceSource(DataSource):
    @classmethod
    def name(cls):
        return "sequence"

    def schema(self):
        kind = "double" if self.options.get("kind") == "uniform_float" else "bigint"
        return f"pos bigint, key {kind}"

    def reader(self, schema):
        return SequenceReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SequenceSource)
