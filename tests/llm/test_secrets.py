import hashlib
import math
import random
import re
import time

from evensort.llm import secret_scan

ASSIGN = re.compile(r"""(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)


def base_spans(t):
    found = [("assign", *m.span()) for m in ASSIGN.finditer(t) if len(m[1]) >= 6]
    found += [("access", *m.span()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
    found += [("hex", *m.span()) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 24]
    return found


def entropy(s):
    return -sum(c / len(s) * math.log2(c / len(s)) for c in (s.count(x) for x in set(s)))


def added_spans(t, base):
    regions = []
    for _, chars, least in secret_scan.CLASSES:
        for m in re.finditer(f"[{chars}]{{{secret_scan.WINDOW},}}", t):
            v, s = m[0], m.start()
            if any(b < m.end() and s < e for _, b, e in base):
                continue
            if re.search(secret_scan.ALLOW, v) or not re.search("[0-9]", v) or not re.search("[A-Za-z]", v):
                continue
            w = secret_scan.WINDOW
            hits = [i for i in range(len(v) - w + 1) if entropy(v[i : i + w]) >= least - 1e-10]
            if hits:
                regions.append((s + hits[0], s + hits[-1] + w))
    out = []
    for s, e in sorted(regions):
        if out and out[-1][1] > s:
            out[-1] = (out[-1][0], max(out[-1][1], e))
        else:
            out.append((s, e))
    return [("entropy", s, e) for s, e in out]


def listed(spans):
    order = secret_scan.KINDS.index
    return ",".join(f"{k}:{s}:{e}" for k, s, e in sorted(spans, key=lambda x: (x[1], order(x[0]), x[2])))


def test_against_brute_force(spark):
    rng = random.Random(4)
    pieces = ["token = \"", "ſecret=", "API_KEY:", "apikey='", "password=abcde", "secret=token: abcdefgh", "AKIA", "AKIA" + "Q7" * 10, "é", "😀", " ", "\n",
              "0123456789abcdef" * 2, "example", "deadbeef-dead-beef-dead-beefdeadbeef", "a" * 40, "Zx9+/kQ2", "=", ":", "the"]
    texts = [None, "", "😀token=abcdef"]
    for _ in range(250):
        t = "".join(rng.choice(pieces) for _ in range(rng.randint(1, 12)))
        if rng.random() < 0.6:
            t += "".join(rng.choice("abcdefghijKLMNOP0123456789+/_-") for _ in range(rng.randint(10, 60)))
        texts.append(t)
    texts += [("ab " * 40_000) + "AKIA" + "A1B2" * 6, texts[5], texts[5]]
    rows = [(i, t, "x") for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, Spans string")
    got = {r.doc_id: r for r in secret_scan.scan(df).collect()}
    assert len(got) == len(texts)
    added = 0
    for i, t in enumerate(texts):
        base = base_spans(t or "")
        more = added_spans(t or "", base)
        added += len(more)
        r = got[i]
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(k == x for k, *_ in base) for x in ("assign", "access", "hex")), t
        assert r.base_sha256 == hashlib.sha256(listed(base).encode()).hexdigest(), t
        assert r.spans == listed(base + more), t
    assert added > 20


def test_redaction_and_empty_table(spark):
    df = spark.createDataFrame([(1, "é token=abcdef. AKIA" + "B2" * 9 + " end"), (2, None), (3, "clean")], "doc_id int, text string")
    out = secret_scan.scan(df).withColumn("text", secret_scan.redact(secret_scan.F.col("text"), secret_scan.F.col("found")))
    assert [r.text for r in out.orderBy("doc_id").collect()] == ["é [SECRET] [SECRET] end", None, "clean"]
    assert secret_scan.scan(df.limit(0)).count() == 0


def test_native_plan(spark):
    df = spark.createDataFrame([(1, "x")], "doc_id int, text string")
    plan = secret_scan.scan(df)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Exchange" not in plan


def test_long_runs_and_many_matches_are_linear(spark):
    rng = random.Random(6)
    chars = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"
    run = "".join(rng.choice(chars) for _ in range(1_000_000))
    many = "token=abcdef " * 50_000
    df = spark.createDataFrame([(1, run), (2, many)], "doc_id int, text string").repartition(2)
    began = time.perf_counter()
    got = {r.doc_id: r for r in secret_scan.scan(df).collect()}
    assert time.perf_counter() - began < 120
    assert got[1].n_entropy == 1 and got[2].n_assign == 50_000
    base = base_spans(many)
    assert got[2].base_sha256 == hashlib.sha256(listed(base).encode()).hexdigest()


def test_other_windows_and_classes(spark):
    rng = random.Random(7)
    texts = ["".join(rng.choice("ab01+/ ") for _ in range(rng.randint(0, 90))) for _ in range(60)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")
    classes = (("two", "ab01", 1.5), ("all", "ab01+/", 2.2))
    got = {r.doc_id: [(x.s, x.e) for x in r.found if x.k == 3] for r in secret_scan.scan(df, window=9, classes=classes).collect()}
    for i, t in enumerate(texts):
        regions = []
        for _, own, least in classes:
            for m in re.finditer(f"[{own}]{{9,}}", t):
                v = m[0]
                if re.search(secret_scan.ALLOW, v) or not re.search("[0-9]", v) or not re.search("[A-Za-z]", v):
                    continue
                hits = [k for k in range(len(v) - 8) if entropy(v[k : k + 9]) >= least - 1e-10]
                if hits:
                    regions.append((m.start() + hits[0], m.start() + hits[-1] + 9))
        out = []
        for s, e in sorted(regions):
            if out and out[-1][1] > s:
                out[-1] = (out[-1][0], max(out[-1][1], e))
            else:
                out.append((s, e))
        assert got[i] == out, t
