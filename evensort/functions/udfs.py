"""Functions for SQL: Arrow lookups, a grouped median, table functions, cogrouped merges."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def _columns(**kinds: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(n, k) for n, k in kinds.items()])


def partition_of(pivots: list):
    """Vectorised lookup for many pivots, where a tree of comparisons would be large."""
    bounds = np.array(sorted(pivots))

    @F.pandas_udf(T.LongType())
    def place(keys: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(bounds, keys.to_numpy(), side="left"))

    return place


@F.pandas_udf(T.DoubleType())
def lower_median(values: pd.Series) -> float:
    """The element of rank ceil(n / 2) of a group.  The group must fit a worker."""
    x = values.dropna().to_numpy()
    return float(np.partition(x, (len(x) + 1) // 2 - 1)[(len(x) + 1) // 2 - 1]) if len(x) else None


@F.udtf(returnType=_columns(k=T.LongType(), pivot_key=T.DoubleType(), cut_rank=T.LongType()))
class ExactCuts:
    """Exact cuts of the rows (key, n_parts) of one table partition."""

    def __init__(self):
        self.keys, self.parts = [], 1

    def eval(self, row: T.Row):
        self.keys.append(row["key"])
        self.parts = row["n_parts"]

    def terminate(self):
        keys, n = np.sort(np.array(self.keys, float)), len(self.keys)
        for k in range(1, self.parts):
            r = -(-k * n // self.parts)
            if n:
                yield k, float(keys[r - 1]), r


@F.udtf(returnType=_columns(pos=T.LongType(), key=T.IntegerType()))
class WorkedExample:
    """The six-element example input."""

    def eval(self):
        yield from enumerate((5, 2, 8, 4, 1, 7))


def register_all(spark: SparkSession) -> None:
    spark.udtf.register("exact_cuts", ExactCuts)
    spark.udtf.register("worked_example", WorkedExample)
    spark.udf.register("lower_median", lower_median)


def cogroup_merge(left: DataFrame, right: DataFrame, group: str) -> DataFrame:
    """Two tables (group, key, pos) merged in each group: left first among equal keys.

    Both sides of a group are in one worker at once; larger groups are for setops.merge_sorted."""
    kinds = {f.name: f.dataType for f in left.schema.fields}
    schema = T.StructType(
        [T.StructField(group, kinds[group]), T.StructField("key", kinds["key"]), T.StructField("side", T.IntegerType()), T.StructField("rnk", T.LongType()), T.StructField("pos", kinds["pos"])]
    )

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        a, b = (x.sort_values(["key", "pos"]).reset_index(drop=True) for x in (a, b))
        at = np.searchsorted(a["key"].to_numpy(), b["key"].to_numpy(), side="right") + np.arange(len(b))
        own = np.setdiff1d(np.arange(len(a) + len(b)), at)
        return pd.concat([a.assign(side=np.int32(0), rnk=own), b.assign(side=np.int32(1), rnk=at)])[[group, "key", "side", "rnk", "pos"]]

    # sides of one parent share column ids, which a cogroup mistakes for one side's columns
    left, right = (x.select(*[F.col(c).alias(c) for c in (group, "key", "pos")]) for x in (left, right))
    return left.groupBy(group).cogroup(right.groupBy(group)).applyInPandas(run, schema)
