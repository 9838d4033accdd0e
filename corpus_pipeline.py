"""From raw documents to a training mix, in five stages over a Parquet table each.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet
and read again as the next one's ``docs``.  All but the last return the columns of
documents: toxic documents go, one of each near-duplicate group stays, documents with
benchmark passages go, secrets are masked (n_chars follows the text), and the rest is mixed
to source targets, one row a copy with its number in ``copy``.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evensort.llm import decontaminate, mixing, secret_scan, simhash, toxicity
from evensort.llm._arrow import column, remove_folder, shared_folder


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _without_clashes(docs: DataFrame, step) -> DataFrame:
    """``step`` of ``docs`` with its own columns only; further ones travel in a struct, so
    none clashes with what the step adds."""
    plain = ["doc_id", "text", "n_chars"]
    own = [c for c in plain if c in docs.columns]
    rest = [c for c in docs.columns if c not in own]
    packed = docs.select(*own, F.struct(*[column(c) for c in rest]).alias("__rest")) if rest else docs
    out = step(packed)
    back = {c: column(c) if c in own else F.col("__rest")[c].alias(c) for c in docs.columns}
    return out.select(*[back[c] for c in docs.columns])


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose text scores under 0.5; the model learns from documents and labels."""
    known = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.fit(known, table(spark, sf_dir, "labels"), train=~toxicity.held_out(F.col("id")))
    return _without_clashes(docs, lambda d: toxicity.score(d, model).where("predicted = 0"))


def keep_one_of_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.deduplicate(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    bench = table(spark, sf_dir, "benchmark")
    return _without_clashes(docs, lambda d: decontaminate.scan(d, bench).where("NOT contaminated"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    def masked(d: DataFrame) -> DataFrame:
        marked = secret_scan.scan(d).withColumn("text", secret_scan.redact(F.col("text"), F.col("found")))
        if "n_chars" not in d.columns:
            return marked
        length = F.char_length("text").cast(d.schema["n_chars"].dataType)
        return marked.withColumn("n_chars", F.when(F.size("found") > 0, length).otherwise(F.col("n_chars")))

    return _without_clashes(docs, masked)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", keep_one_of_near_duplicates),
    ("decontamination", drop_contaminated),
    ("secrets", mask_secrets),
    ("mixing", mix_sources),
]

#: Trained scores and SimHash components have no SQL form; tests check run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written to and read from the shared folder.

    A stage's table is deleted when the next one's is written; the last one's stays, as the
    rows returned are read from it."""
    docs, before = table(spark, sf_dir, "documents"), None
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        path = f"{folder}/{name}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if before is not None:
            remove_folder(spark, before)
        before = path
    return docs
