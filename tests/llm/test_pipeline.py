import pytest
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from evensort.llm import decontaminate, mixing, secret_scan, toxicity

from .test_secrets import added_spans, base_spans
from .test_simhash import brute_components, brute_fp


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    at = tmp_path_factory.mktemp("tables")
    bad = lambda i: f"zzbad{'abc'[i % 3]} zzbad{'bca'[i % 3]}"
    body = lambda i: " ".join(f"w{i * 37 + j * j % 29}x{j % (i % 7 + 3)}" for j in range(30))
    bench = " ".join(f"q{j}" for j in range(14))
    rows = [(i, body(i) + (" " + bad(i) if i % 5 == 0 else ""), "en", f"src{i % 3}", 0, 1.5) for i in range(150)]
    rows += [(200 + i, body(7) + " tail", "en", "src1", 0, None) for i in range(12)]
    rows += [(300 + i, body(160 + i) + " " + bench + " end", None, None, 0, 2.0) for i in range(4)]
    rows += [(400 + i, f"{body(170 + i)} token=abc{i}defgh AKIA{'Q7' * 9}", "de", "src2", 0, 0.0) for i in range(4)]
    rows += [(None, None, None, None, None, None), (500, "", "en", "src0", 0, 0.0), (501, " ", "en", "src0", 1, 0.0), (502, body(180), "en", "src2", 0, 0.0), (502, body(180), "en", "src2", 0, 0.0)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint, score double")
    docs.withColumn("n_chars", F.char_length("text").cast("bigint")).write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame([(i, 1, int(i % 5 == 0)) for i in range(150)], "doc_id bigint, quality int, toxic int").write.parquet(f"{at}/labels.parquet")
    spark.createDataFrame([(1, bench), (2, None)], "item_id bigint, text string").write.parquet(f"{at}/benchmark.parquet")
    return str(at)


def redacted(t):
    base = base_spans(t)
    spans, out, at = sorted((s, e) for _, s, e in base + added_spans(t, base)), "", 0
    merged = []
    for s, e in spans:
        if merged and merged[-1][1] > s:
            merged[-1][1] = max(merged[-1][1], e)
        else:
            merged.append([s, e])
    for s, e in merged:
        out, at = out + t[at:s] + "[SECRET]", e
    return out + t[at:]


def test_stages_equal_brute_force(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    names = docs.columns
    bench = decontaminate.Scanner([("1", " ".join(f"q{j}" for j in range(14)).encode())])
    rows = [tuple(r) for r in docs.collect()]
    for name, stage in pipeline.STAGES:
        made = stage(spark, docs, folder)
        got = [tuple(r) for r in made.collect()]
        if name == "toxicity":
            known = spark.read.parquet(f"{folder}/labels.parquet")
            model = toxicity.fit(docs.select("doc_id", "text"), known, train=~toxicity.held_out(F.col("id")))
            vectors = toxicity.Vectors(model.terms)
            want = [r for r in rows if model.score(vectors((r[1] or "").encode()))[0] < 0.5]
            assert not any("zzbad" in (r[1] or "") for r in want) and len(want) >= 130
        elif name == "near_duplicates":
            root = brute_components([brute_fp(r[1]) for r in rows])
            groups = {}
            for r in rows:
                groups.setdefault(root[brute_fp(r[1])], []).append(r)
            want = [min(g, key=lambda r: (r[0] is None, r[0] or 0)) for g in groups.values()]
        elif name == "decontamination":
            want = [r for r in rows if not bench((r[1] or "").encode())[4]]
            assert len(want) == len(rows) - 4
        elif name == "secrets":
            want = [r if r[1] is None or redacted(r[1]) == r[1] else (r[0], redacted(r[1]), *r[2:4], len(redacted(r[1])), r[5]) for r in rows]
            assert sum("[SECRET]" in (r[1] or "") for r in want) == 4
        else:
            copies = {r.id: r.copies for r in mixing.plan(docs).collect()}
            want = [(*r, c) for r in rows for c in range(1, copies[r[0]] + 1)]
        assert made.columns == (names if name != "mixing" else [*names, "copy"])
        assert sorted(got, key=str) == sorted(want, key=str), name
        if name != "mixing":
            docs = spark.createDataFrame(got, docs.schema)
            rows = got


def test_run_and_empty_tables(spark, folder, tmp_path):
    assert pipeline.run(spark, folder).count() > 100
    for t in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{folder}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    assert pipeline.run(spark, str(tmp_path)).count() == 0
