"""A streaming k-way merge of files that are each sorted by one column."""

from __future__ import annotations

import heapq
from collections.abc import Iterator, Sequence

import pyarrow as pa
import pyarrow.parquet as pq


def _rows(path: str, key: str, order: int, batch_rows: int) -> Iterator[tuple]:
    n = 0
    for batch in pq.ParquetFile(path).iter_batches(batch_rows):
        names = batch.schema.names
        for row in zip(*(batch.column(c).to_pylist() for c in names)):
            yield row[names.index(key)], order, n, row
            n += 1


def merge_sorted_files(paths: Sequence[str], key: str, batch_rows: int = 8192) -> Iterator[pa.RecordBatch]:
    """Batches in key order; files go in the given order among equal keys.  One batch of each
    file is held at a time.  Keys must not be null."""
    if not paths:
        return
    schema = pq.read_schema(paths[0])
    held: list[tuple] = []
    for _, _, _, row in heapq.merge(*(_rows(p, key, i, batch_rows) for i, p in enumerate(paths))):
        held.append(row)
        if len(held) == batch_rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*held), schema)], schema=schema)
            held = []
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*held), schema)], schema=schema)
