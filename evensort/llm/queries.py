"""The fixed queries opN_<name> over whole tables, derived from the operators' outputs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, langid, licenses, mixing, ogg, pii, secret_scan, simhash, toxicity, warc
from ._arrow import checkpoint, remove_folder


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = toxicity.classify(docs, table(spark, sf_dir, "labels"), keep=["doc_id"])
    return out.select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"), keep=["doc_id"]).drop("expressions")


def op3_warc_salvage(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = warc.new_folder(spark)
    warc.write(table(spark, sf_dir, "pages"), path)
    # a gap in archives just written would be lost pages
    lost = F.raise_error(F.concat(F.lit("gap in "), F.col("path"), F.lit(": "), F.col("reason")))
    records = warc.read(spark, path).withColumn("kind", F.when(F.col("kind") == "gap", lost).otherwise(F.col("kind")))
    number = lambda c: F.when(F.col(c) != "null", F.col(c)).cast("bigint").alias(c)
    own = records.where("kind = 'record'").select(number("page_id"), "payload_bytes", "payload_digest", "record_type", number("refers_to"))
    made = checkpoint(own)
    remove_folder(spark, path)
    return made


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = langid.fit(docs, train=~langid.held_out(F.col("doc_id")))
    out = langid.predict(docs, model, keep=["doc_id"])
    return out.select("doc_id", langid.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def op5_ogg_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    media = ogg.encode(table(spark, sf_dir, "documents"), keep=["doc_id"])
    return ogg.describe(media, keep=["doc_id"]).drop("damaged_pages")


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    fingerprint = F.lower(F.lpad(F.hex("__fp"), 16, "0")).alias("fingerprint")
    return found.select("doc_id", fingerprint, "component_id")


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(table(spark, sf_dir, "documents"), keep=["doc_id"]).drop("found")


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = decontaminate.scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), keep=["doc_id"])
    return out.drop("items", "hits")


def op9_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return pii.scan(docs, pii.fit(docs), keep=["doc_id"]).drop("found")


def op10_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixing.plan(table(spark, sf_dir, "documents"))
    return out.selectExpr("id AS doc_id", "size", "source_size", "target", "copies * size AS taken")


QUERIES = {
    "op1_toxicity": op1_toxicity,
    "op2_license_scan": op2_license_scan,
    "op3_warc_salvage": op3_warc_salvage,
    "op4_language_id": op4_language_id,
    "op5_ogg_columns": op5_ogg_columns,
    "op6_simhash": op6_simhash,
    "op7_secret_scan": op7_secret_scan,
    "op8_decontaminate": op8_decontaminate,
    "op9_personal_data": op9_personal_data,
    "op10_mix_sources": op10_mix_sources,
}

_WORDS = "regexp_extract_all(translate({t}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')"

ORACLE_SQL = {
    "op8_decontaminate": f"""
        WITH d AS (SELECT row_number() OVER () AS r, doc_id, {_WORDS.format(t="coalesce(text, '')")} AS w FROM documents),
        i AS (SELECT CAST(item_id AS VARCHAR) AS item, {_WORDS.format(t="coalesce(text, '')")} AS w FROM benchmark),
        n AS (SELECT *, least(len(w), 10) AS k FROM i WHERE len(w) > 0),
        g AS (SELECT DISTINCT item, k, array_to_string(w[s : s + k - 1], ' ') AS gram
              FROM (SELECT *, unnest(range(1, len(w) - k + 2)) AS s FROM n)),
        q AS (SELECT DISTINCT k FROM g),
        p AS (SELECT r, k, w, unnest(range(1, CAST(len(w) - k + 2 AS BIGINT))) AS s FROM d, q WHERE len(w) >= k),
        h AS (SELECT p.r, p.k, p.s, g.item FROM p JOIN g ON p.k = g.k AND array_to_string(p.w[p.s : p.s + p.k - 1], ' ') = g.gram),
        c AS (SELECT r, count(*) AS n_hit FROM (SELECT DISTINCT r, unnest(range(s, s + k)) AS x FROM h) GROUP BY r),
        t AS (SELECT r, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS ids FROM (SELECT DISTINCT r, item FROM h) GROUP BY r)
        SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
               sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
        FROM d LEFT JOIN c USING (r) LEFT JOIN t USING (r)""",
    "op10_mix_sources": r"""
        WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size FROM documents),
        s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
        o AS (SELECT *, [3, 1, 2][CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS INTEGER)] AS w,
                     CAST(source_size AS DOUBLE) * 2 AS top, CAST(sum(source_size) OVER () AS DOUBLE) * 1.5::DOUBLE AS budget FROM s),
        p AS (SELECT *, row_number() OVER f AS k,
                     coalesce(sum(top) OVER (ORDER BY top / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before,
                     sum(w) OVER (ORDER BY top / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest
              FROM o WINDOW f AS (ORDER BY top / w, source NULLS LAST)),
        l AS (SELECT *, (budget - before) / CAST(rest AS DOUBLE) AS level FROM p),
        e AS (SELECT arg_min(level, k) AS shared FROM l WHERE top > level * w),
        t AS (SELECT source, source_size, coalesce(least(top, shared * w), top) AS target,
                     CAST(CAST('0x' || substr(md5('mix-1' || coalesce(':' || source, '')), 1, 8) AS BIGINT) AS DOUBLE) / 4294967296.0::DOUBLE AS u FROM l, e),
        r AS (SELECT d.doc_id, d.size, t.source_size, t.target, t.u,
                     CAST(row_number() OVER (PARTITION BY d.source ORDER BY d.size, d.doc_id NULLS FIRST) AS DOUBLE) AS k,
                     CASE WHEN t.source_size > 0 THEN t.target / CAST(t.source_size AS DOUBLE) ELSE 0.0::DOUBLE END AS rate
              FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
        SELECT doc_id, size, source_size, target, CAST(floor(k * rate + u) - floor((k - 1) * rate + u) AS BIGINT) * size AS taken FROM r""",
}
