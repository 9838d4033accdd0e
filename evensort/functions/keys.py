"""Order-preserving key codecs, portable integer mixing and sort keys of many columns."""

from __future__ import annotations

import datetime
import json
import math
from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Multipliers of the portable mix (products stay under 2^63).
MIX = (1103515245, 12345, 73244475, 48271)
WORD32 = 1 << 32


def mix32(x: Column) -> Column:
    """A pseudo-random integer in [0, 2^32) that any SQL engine computes alike."""
    a, c, b, d = MIX
    h = F.pmod(x.cast("bigint") * a + c, F.lit(WORD32))
    h = F.pmod(h.bitwiseXOR(F.shiftright(h, 16)) * b, F.lit(WORD32))
    h = F.pmod(h.bitwiseXOR(F.shiftright(h, 15)) * d, F.lit(WORD32))
    return h.bitwiseXOR(F.shiftright(h, 16))


def mix62(x: Column, n: int) -> Column:
    """62 pseudo-random bits from two mixes; ``n`` is the offset of the second input."""
    return mix32(x) * (1 << 30) + F.pmod(mix32(x + n), F.lit(1 << 30))


def ordered_long(key: Column, kind: T.DataType) -> Column:
    """A long that sorts as ``key`` does; numbers, dates, times and booleans only.

    Doubles use their bit pattern: the sign bit flips positives up, all bits flip negatives.
    -0.0 equals 0.0 and NaN is the largest, as in Spark's order; nulls stay null.
    """
    if isinstance(kind, T.FloatType):
        key, kind = key.cast("double"), T.DoubleType()
    if isinstance(kind, T.DoubleType):
        return _double_bits(key)
    if isinstance(kind, T.DecimalType):
        if kind.precision > 18:
            raise TypeError("decimals over 18 digits have no long code")
        return (key * F.lit(10**kind.scale).cast("decimal(20,0)")).cast("bigint")
    if isinstance(kind, T.DateType):
        return F.unix_date(key).cast("bigint")
    if isinstance(kind, T.TimestampNTZType):
        # from its parts: a cast to TIMESTAMP would bend at the session zone's clock changes
        seconds = F.hour(key) * 3600 + F.minute(key) * 60
        micros = (F.extract(F.lit("SECOND"), key) * 1_000_000).cast("bigint")
        return (F.unix_date(key.cast("date")).cast("bigint") * 86_400 + seconds) * 1_000_000 + micros
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(key)
    if isinstance(kind, (T.IntegralType, T.BooleanType)):
        return key.cast("int").cast("bigint") if isinstance(kind, T.BooleanType) else key.cast("bigint")
    raise TypeError(f"no long code for {kind.simpleString()}")


def _double_bits(key: Column) -> Column:
    # hex(double) has no bit form in SQL, so the code is exponent and mantissa as integers
    size = F.abs(key)
    # the smallest normal number's exponent; subnormals share it and have smaller mantissas
    exponent = F.greatest(F.floor(F.log2(size)), F.lit(-1022))
    # log2 may be off by one next to powers of two
    exponent = exponent + F.when(F.pow(F.lit(2.0), exponent + 1) <= size, 1).when(F.pow(F.lit(2.0), exponent) > size, -1).otherwise(0)
    exponent = F.greatest(exponent, F.lit(-1022))
    half = F.floor(exponent / 2)
    mantissa = size / F.pow(F.lit(2.0), half) / F.pow(F.lit(2.0), exponent - half) * float(1 << 52)
    code = (exponent + 1023).cast("bigint") * (1 << 52) + mantissa.cast("bigint") - F.lit(1 << 52)
    top = F.lit(2047 << 52)
    code = F.when(size == 0, F.lit(0)).when(F.isnan(key), top + 1).when(size == float("inf"), top).otherwise(code + 1)
    return F.when(key < 0, -code).otherwise(code).cast("bigint")


def u64_to_ordered_long(key: Column) -> Column:
    """An unsigned 64-bit number held as decimal(20,0) as a long of the same order."""
    return (key.cast("decimal(20,0)") - F.lit(str(1 << 63)).cast("decimal(20,0)")).cast("bigint")


def ordered_long_to_u64(code: Column) -> Column:
    return (code.cast("decimal(20,0)") + F.lit(str(1 << 63)).cast("decimal(20,0)")).cast("decimal(20,0)")


@dataclass(frozen=True)
class By:
    """One sort column: ascending, nulls first unless stated."""

    column: str
    desc: bool = False
    nulls_last: bool = False


def sort_key(df: DataFrame, by: Sequence[By | str]) -> Column:
    """One ascending key column (a struct for several) equivalent to the listed order."""
    specs = [By(b) if isinstance(b, str) else b for b in by]
    for s in specs:
        if s.column not in df.columns:
            raise ValueError(f"unknown sort column {s.column}")
        if isinstance(df.schema[s.column].dataType, (T.MapType, T.VariantType)):
            raise TypeError(f"{s.column} can't be ordered")
    if len(specs) == 1 and not specs[0].desc and not specs[0].nulls_last:
        return F.col(specs[0].column)
    parts = []
    for i, s in enumerate(specs):
        c = F.col(s.column)
        if s.nulls_last:
            parts.append(c.isNull().cast("int").alias(f"n{i}"))
        parts.append((reversed_key(c, df.schema[s.column].dataType) if s.desc else c).alias(f"k{i}"))
    return F.struct(*parts)


def reversed_key(c: Column, kind: T.DataType) -> Column:
    """A key whose ascending order is the descending order of ``c``; nulls stay null."""
    if isinstance(kind, T.StringType):
        digits = F.hex(c.cast("binary"))
        # the mark after the end sorts a prefix behind its extensions
        return F.concat(F.translate(digits, "0123456789ABCDEF", "FEDCBA9876543210"), F.lit("G"))
    if isinstance(kind, (T.DateType, T.TimestampType, T.TimestampNTZType, T.BooleanType)):
        return -ordered_long(c, kind)
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        return F.struct((~F.isnan(c)).alias("number"), F.when(F.isnan(c), F.lit(0.0)).otherwise(-c).alias("v"))
    if isinstance(kind, T.IntegralType):
        # the smallest number has no negative
        return F.bitwise_not(c)
    return -c


def literal(value, kind: T.DataType) -> Column:
    """A collected value as a literal of its type, structs included."""
    if isinstance(kind, T.StructType):
        return F.struct(*[literal(value[f.name], f.dataType).alias(f.name) for f in kind.fields])
    if value is None or isinstance(kind, (T.FloatType, T.DoubleType, T.StringType, T.IntegralType, T.BooleanType, T.TimestampType)):
        return F.lit(value).cast(kind)
    if isinstance(kind, T.ArrayType):
        return F.array(*[literal(v, kind.elementType) for v in value]).cast(kind)
    return F.lit(str(value)).cast(kind)


READ = "__read"


def settled(df: DataFrame) -> DataFrame:
    """``df`` whose computed columns are evaluated once a row under ``held`` filters.

    A filter is pushed below a projection by copying the key's expression into each of its
    comparisons.  A partition id in the projection, used by the filter, stops that."""
    return df.withColumn(READ, F.spark_partition_id())


def held(condition: Column) -> Column:
    return condition & (F.col(READ) >= 0)


def count_bounds(x: Column, bounds: Sequence[Column], strict: bool) -> Column:
    """How many of the rising ``bounds`` lie below ``x`` (``strict``), or at or below it.

    A balanced tree of comparisons: log2 of the bounds' number is evaluated for a row.
    """

    def tree(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        passed = bounds[mid] < x if strict else bounds[mid] <= x
        return F.when(passed, tree(mid + 1, hi)).otherwise(tree(lo, mid))

    return tree(0, len(bounds)).cast("bigint")


#: Up to so many bounds are a tree of comparisons; more are a sorted array that is searched.
TREE = 64


def sorted_array(values: Sequence, kind: T.DataType) -> Column:
    """Values as one constant array, parsed by the engine (a literal for each would make a
    plan of as many nodes)."""
    if isinstance(kind, T.TimestampType) or not _has_text(kind):
        return F.array(*[literal(v, kind) for v in values])
    return F.from_json(F.lit(json.dumps([_text(v, kind) for v in values])), T.ArrayType(kind))


def _has_text(kind: T.DataType) -> bool:
    if isinstance(kind, T.StructType):
        return all(_has_text(f.dataType) for f in kind.fields)
    return isinstance(kind, (T.IntegralType, T.FractionalType, T.StringType, T.BooleanType, T.DateType, T.TimestampNTZType))


def _text(value, kind: T.DataType):
    """A value as JSON has it."""
    if value is None:
        return None
    if isinstance(kind, T.StructType):
        return {f.name: _text(value[f.name], f.dataType) for f in kind.fields}
    if isinstance(value, (datetime.date, datetime.datetime)):
        return value.isoformat()
    if isinstance(value, float) and not math.isfinite(value):
        return "NaN" if math.isnan(value) else "Infinity" if value > 0 else "-Infinity"
    return value if isinstance(value, (int, float, str)) else str(value)


def with_count(df: DataFrame, name: str, x: Column, values: Sequence, kind: T.DataType, strict: bool = True) -> DataFrame:
    """``df`` with ``name``: how many of the rising ``values`` lie below ``x``, or at or below it.

    A binary search in one constant array, unrolled: a projection a step, all in one stage of
    generated code, so that 100,000 values cost a row 17 comparisons and the plan 17 nodes."""
    if len(values) <= TREE:
        return df.withColumn(name, count_bounds(x, [literal(v, kind) for v in values], strict))
    n, step = len(values), 1 << (len(values).bit_length() - 1)
    out = df.withColumns({"__x": x, "__in": sorted_array(values, kind), "__lo": F.lit(0)})
    while step:
        to = F.col("__lo") + step
        mid = F.element_at("__in", F.least(to, F.lit(n)))
        passed = mid < F.col("__x") if strict else mid <= F.col("__x")
        out = out.withColumn("__lo", F.when((to <= n) & passed, to).otherwise(F.col("__lo")))
        step //= 2
    # a filter on the result would be pushed below and copy every step into the next one's two
    # places; a partition id in the same projection stops that
    stop = F.when(F.spark_partition_id() < 0, 1).otherwise(0)
    return out.withColumn(name, (F.col("__lo") + stop).cast("bigint")).drop("__x", "__in", "__lo")
