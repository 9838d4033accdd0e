"""Parallel sorting with balanced splitting on Spark DataFrames.

A sequence is cut into blocks, pivots or exact cuts are chosen, rows are routed to
partitions in one shuffle, and each partition is merged and given its global offset.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence


def _packed(df, by: Sequence, pos: str | None):
    """The columns' names, and the sequence with them as c0, c1, ...: none clashes with its own."""
    from dataclasses import replace

    from .functions.keys import By
    from .operators import sorter

    names = df.columns
    plain = df.toDF(*[f"c{i}" for i in range(len(names))])
    specs = [By(b) if isinstance(b, str) else b for b in by]
    for s in specs:
        if s.column not in names:
            raise ValueError(f"unknown sort column {s.column}")
    specs = [replace(s, column=f"c{names.index(s.column)}") for s in specs]
    return names, sorter.sequence(plain, specs, None if pos is None else f"c{names.index(pos)}")


def sort(by: Sequence, pos: str | None = None, **how) -> Callable:
    """For ``df.transform``: the rows with ``part`` and ``rnk`` of the order ``by``.

    ``by`` has names or :class:`evensort.functions.keys.By`; ``pos`` names a dense unique
    column that breaks ties (else the rows' places in the scan); ``how`` goes to
    :func:`evensort.operators.sorter.parallel_sort`."""
    from .operators import sorter

    def run(df):
        names, packed = _packed(df, by, pos)
        out = sorter.parallel_sort(packed, **how).df
        return out.select(*[out[f"c{i}"].alias(c) for i, c in enumerate(names)], "part", "rnk")

    return run


def top(by: Sequence, k: int, pos: str | None = None, **how) -> Callable:
    """For ``df.transform``: the first ``k`` rows of the order, from the partitions that hold them."""
    from .operators import rank, sorter

    def run(df):
        names, packed = _packed(df, by, pos)
        out = rank.top_k(sorter.parallel_sort(packed, **how), k)
        return out.select(*[out[f"c{i}"].alias(c) for i, c in enumerate(names)], "rnk")

    return run


def quantiles(column: str, shares: Sequence[float]) -> Callable:
    """For ``df.transform``: (share, value) of exact quantiles, elements of the column."""
    from pyspark.sql import types as T

    from .operators import rank

    def run(df):
        own = df.where(df[column].isNotNull()).select(df[column].alias("key"))
        schema = T.StructType([T.StructField("share", T.DoubleType()), T.StructField("value", df.schema[column].dataType)])
        return df.sparkSession.createDataFrame(list(zip(map(float, shares), rank.exact_quantiles(own, list(shares)))), schema)

    return run
