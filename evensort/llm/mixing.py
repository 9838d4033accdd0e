"""Mixing sources to target weights by systematic sampling.

Every source gets a target of words; within it each document expects target / source size
copies.  Documents are put in (size, id) order, expected copies are prefix-summed, one
offset per source is added, and a document is emitted once for each integer boundary its
own step crosses.  Size order makes the sample follow the size distribution, so the words
taken stay within about one document's size of the target.

Ranks are made without a window over a source: rows are range-partitioned by (source, size,
id), counted for each (partition, source), and places inside a partition are shifted by the
counts of the partitions before.  So a source with a third of all rows spreads over many tasks.

Defined cases: a null text has size 0; a null source is a source of its own, last in order;
a null id sorts first; rows equal in all three columns are interchangeable; sources of size
0 get target 0; an empty table gives an empty result; other columns take no part.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._arrow import checkpoint, column, packed, unpacked

WEIGHTS = (3, 1, 2)
BUDGET = 1.5
CAP = 2.0
SEED = "mix-1"
WORD = r"[^\x20\x09-\x0D]+"


def source_targets(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, cap: float = CAP, seed: str = SEED) -> DataFrame:
    """(source, source_size, target, u) from rows (source, size); one row per source.

    Targets are the level filling of caps: with sources in order of cap / weight, those
    before the first that stays under its cap are full, the rest share by weight.
    """
    cases = " ".join(f"WHEN {i} THEN {w}" for i, w in enumerate(weights))
    total = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    query = f"""
        WITH o AS (SELECT source, source_size,
                   CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % {len(weights)} {cases} END AS w
                   FROM {{total}}),
        c AS (SELECT *, {cap!r}D * source_size AS top, sum(source_size) OVER () * {budget!r}D AS budget FROM o),
        p AS (SELECT *, row_number() OVER (ORDER BY top / w, source NULLS LAST) AS k,
                     coalesce(sum(top) OVER (ORDER BY top / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0D) AS before,
                     sum(w) OVER (ORDER BY top / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest
              FROM c),
        l AS (SELECT *, (budget - before) / rest AS level FROM p),
        f AS (SELECT *, min(CASE WHEN top > level * w THEN k END) OVER () AS first_open FROM l),
        g AS (SELECT *, min(CASE WHEN k = first_open THEN level END) OVER () AS shared FROM f)
        SELECT source, source_size, coalesce(least(top, shared * w), top) AS target,
               conv(substr(md5(concat('{seed}', coalesce(concat(':', source), ''))), 1, 8), 16, 10) / 4294967296D AS u
        FROM g"""
    return sizes.sparkSession.sql(query, total=total)


def plan(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", carry: dict | None = None, **how
) -> DataFrame:
    """One row per document: id, source, size, rank in its source, source_size, target, copies.

    ``carry`` names further expressions of ``docs`` that the rows keep.
    """
    spark = docs.sparkSession
    carry = carry or {}
    size = F.coalesce(F.regexp_count(column(text_col), F.lit(WORD)), F.lit(0)).cast("bigint")
    own = [column(id_col).alias("id"), column(source_col).alias("source"), size.alias("size")]
    rows = checkpoint(docs.select(*own, *[e.alias(n) for n, e in carry.items()]))
    targets = checkpoint(source_targets(rows, **how))
    order = ["source", "size", "id"]
    # a row's partition and its place there are written with it
    laid = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    laid = checkpoint(laid.withColumns({"part": F.spark_partition_id(), "place": F.monotonically_increasing_id()}))
    before = Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = laid.groupBy("part", "source").agg(F.count("*").alias("n"), F.min("place").alias("first"))
    starts = starts.select("part", "source", "first", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    starts = starts.join(targets.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s"))).drop("s")

    s = starts.withColumnsRenamed({"part": "p", "source": "s"})
    out = laid.join(s, (F.col("part") == F.col("p")) & F.col("source").eqNullSafe(F.col("s")))
    rank = F.col("start") + F.col("place") - F.col("first") + 1
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    copies = F.floor(rank * rate + F.col("u")) - F.floor((rank - 1) * rate + F.col("u"))
    return out.select(
        "id", "source", "size", rank.alias("rank"), "source_size", "target", copies.cast("bigint").alias("copies"), *carry
    )


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **how) -> DataFrame:
    """The mixed corpus: each document once per copy, with ``copy`` numbering them from 1.

    Copies are decided on narrow rows keyed by id, source, size and a hash of the text.
    Rows equal in that key are one group whose copies are handed to its first row.
    """
    size = F.coalesce(F.regexp_count(column(text_col), F.lit(WORD)), F.lit(0)).cast("bigint")
    named = {"own_id": column(id_col), "own_source": column(source_col), "own_size": size, "own_text": F.xxhash64(column(text_col))}
    own = packed(docs, **named)
    narrow = docs.select(column(id_col).alias("id"), column(text_col).alias("text"), column(source_col).alias("source"))
    chosen = plan(narrow, "id", "text", "source", {"hash": F.xxhash64("text")}, **how)
    name = ["id", "source", "size", "hash"]
    chosen = checkpoint(chosen.groupBy(*name).agg(F.sum("copies").alias("copies"), F.count("*").alias("rows")))
    if chosen.where("rows > 1").limit(1).count():
        own = own.dropDuplicates(list(named))
    match = F.lit(True)
    for a, b in zip(named, name):
        match = match & F.col(a).eqNullSafe(F.col(b))
    joined = own.join(chosen.where("copies > 0"), match)
    joined = joined.withColumn("number", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
    return unpacked(joined, [c for c in docs.columns if c.lower() != "copy"], F.col("number").alias("copy"))
