"""Step 1: contiguous blocks of a sequence, and sorting them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.keys import ordered_long
from . import kernels


def block_length(n: int, n_blocks: int) -> int:
    if n_blocks < 1:
        raise ValueError("n_blocks must be at least 1")
    return max(1, -(-n // n_blocks))


def assign_blocks(df: DataFrame, n_blocks: int, n: int | None = None, pos: str = "pos") -> DataFrame:
    """``block`` = pos div ceil(n / n_blocks); trailing blocks may be empty."""
    length = block_length(df.count() if n is None else n, n_blocks)
    return df.withColumn("block", F.expr(f"`{pos}` div {length}"))


def layout(blocked: DataFrame) -> DataFrame:
    """(block, n, min_pos, max_pos) of each block that has rows."""
    return blocked.groupBy("block").agg(F.count("*").alias("n"), F.min("pos").alias("min_pos"), F.max("pos").alias("max_pos"))


def sort_blocks(blocked: DataFrame, kernel: str = "spark") -> DataFrame:
    """``blocked`` with ``idx``, each row's 0-based place in its sorted block.

    ``spark`` is the engine's own sorter, which spills.  Other kernels sort a block's key
    codes in Arrow batches and need the block in a worker's memory; keys must be numeric.
    """
    if kernel == "spark":
        order = Window.partitionBy("block").orderBy("key", "pos")
        return blocked.withColumn("idx", F.row_number().over(order).cast("bigint") - 1)
    coded = blocked.withColumn("code", ordered_long(F.col("key"), blocked.schema["key"].dataType))
    schema = blocked.withColumn("idx", F.lit(0).cast("bigint")).schema
    names = blocked.columns

    def run(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("pos", kind="stable")
        # no code: a null key, which is the smallest
        codes = part["code"].fillna(-(1 << 63)) if part["code"].hasnans else part["code"]
        order = kernels.permutation(kernel, codes.to_numpy(np.int64))
        out = part.iloc[order][names].copy()
        out["idx"] = np.arange(len(out), dtype=np.int64)
        return out

    return coded.groupBy("block").applyInPandas(run, schema)
