"""Shared plumbing of the operators: appending columns in Arrow batches, checkpoints."""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator, Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StringType, StructField, StructType

ROW = "__row"
#: Rows and about the bytes handed to a kernel at once; they bound the Python objects alive
#: beside a batch, however long its texts are.
SLICE_ROWS = 256
SLICE_BYTES = 8 << 20


def quoted(name: str) -> str:
    """A column name safe for F.col, dots and backticks included."""
    return "`" + name.replace("`", "``") + "`"


def column(name: str):
    return F.col(quoted(name))


def without(columns: Sequence[str], names: Sequence[str]) -> list[str]:
    """``columns`` that don't clash with ``names`` (Spark compares without case)."""
    taken = {n.lower() for n in names}
    return [c for c in columns if c.lower() not in taken]


def packed(df: DataFrame, **named: Column) -> DataFrame:
    """``df``'s columns in a struct, where they clash with nothing, beside ``named`` ones."""
    row = F.struct(*[column(c) for c in df.columns]) if df.columns else F.struct(F.lit(0).alias("none"))
    return df.select(row.alias(ROW), *[c.alias(n) for n, c in named.items()])


def unpacked(df: DataFrame, columns: Sequence[str], *more: Column) -> DataFrame:
    """The named columns of a packed frame, and ``more``."""
    return df.select(*[F.col(ROW)[c].alias(c) for c in columns], *more)


def _as_list(array: pa.Array, as_bytes: bool) -> list:
    if as_bytes and pa.types.is_string(array.type):
        array = array.cast(pa.binary())
    elif as_bytes and pa.types.is_large_string(array.type):
        array = array.cast(pa.large_binary())
    return array.to_pylist()


def append_columns(
    df: DataFrame,
    inputs: Sequence[str],
    make: Callable[[], Callable],
    fields: StructType,
    keep: Sequence[str] | None = None,
    as_bytes: bool = True,
) -> DataFrame:
    """Append the columns that a kernel computes from ``inputs``, in one narrow pass.

    ``make()`` runs once per task and returns the kernel, which maps lists of input
    values (strings as UTF-8 bytes unless ``as_bytes`` is false) to a list of rows
    (tuples in the order of ``fields``).  ``keep`` are the columns passed through
    (default: all).  A kept column with the name of a new one gives way to it.
    """
    keep = without(df.columns if keep is None else keep, fields.names)
    extra = [c for c in inputs if c not in keep]
    row = F.struct(*[column(c) for c in keep]) if keep else F.struct(F.lit(0).alias("none"))
    source = df.select(row.alias(ROW), *[column(c).alias(f"__in{i}") for i, c in enumerate(extra)])
    schema = StructType([StructField(ROW, source.schema[ROW].dataType, False), *fields.fields])
    names, most_rows, most_bytes = list(inputs), SLICE_ROWS, SLICE_BYTES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_type

        kernel = make()
        types = [to_arrow_type(f.dataType) for f in fields.fields]
        for whole in batches:
            row_bytes = whole.nbytes // max(1, whole.num_rows)
            slice_rows = max(1, min(most_rows, most_bytes // max(1, row_bytes)))
            for at in range(0, whole.num_rows, slice_rows):
                batch = whole.slice(at, slice_rows)
                rows = batch.column(0)
                columns = [
                    _as_list(rows.field(keep.index(c)) if c in keep else batch.column(1 + extra.index(c)), as_bytes)
                    for c in names
                ]
                made = kernel(*columns)
                arrays = [pa.array([r[i] for r in made], t) for i, t in enumerate(types)]
                yield pa.RecordBatch.from_arrays([rows, *arrays], names=[ROW, *fields.names])

    out = source.mapInArrow(run, schema)
    return out.select(*[F.col(ROW)[c].alias(c) for c in keep], *[column(n) for n in fields.names])


def checkpoint(df: DataFrame) -> DataFrame:
    """``df.checkpoint()`` in the shared folder the session names.

    A folder of this machine is set only where none is named, as in tests.
    """
    spark = df.sparkSession
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        context.setCheckpointDir(shared_folder(spark))
    return df.checkpoint()


_LOCAL: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir, else (local masters only) a temporary one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    if not _LOCAL:
        _LOCAL.append(tempfile.mkdtemp(prefix="evensort-"))
    return _LOCAL[0]


def remove_folder(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared file system, if it is there."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def strings(*names: str) -> StructType:
    return StructType([StructField(n, StringType()) for n in names])
