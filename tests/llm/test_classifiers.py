import os
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from evensort.llm import langid, toxicity

SF = "/root/testdata/sf0.01"


def test_nearest_equals_full_search():
    rng = random.Random(1)
    vectors = [{rng.randrange(40): rng.randint(1, 4) for _ in range(rng.randint(0, 8))} for _ in range(700)]
    index = toxicity.Index(vectors, 40, block=16)
    dense = np.zeros((700, 40))
    for i, v in enumerate(vectors):
        t, w = index.weigh(v)
        dense[i, t] = w
    for q in vectors[:60] + [{1: 9}, {}]:
        t, w = index.weigh(q)
        full = np.zeros(40)
        full[t] = w
        scores = dense @ full
        near, similarity = index.nearest(q, 7)
        want = [i for i in np.argsort(-scores, kind="stable") if scores[i] > 1e-12][:7]
        assert np.allclose(similarity, scores[want]) and np.allclose(scores[near], similarity)


def test_isotonic_rises_and_keeps_the_mean():
    rng = np.random.default_rng(2)
    x = rng.random(300).round(2)
    y, w = (rng.random(300) < x).astype(float), rng.random(300) + 0.1
    ends, values = toxicity.isotonic(x, y, w)
    assert (np.diff(values) >= -1e-12).all() and (np.diff(ends) >= 0).all()
    assert abs((np.interp(x, ends, values) * w).sum() - (y * w).sum()) < 1e-6 * w.sum() + 1e-6


def test_toxicity_cases(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    text = lambda bad: " ".join([word() for _ in range(20)] + (["zzbad" + rng.choice("abc")] if bad else []))
    rows = [(i, text(i % 4 == 0), i) for i in range(400)] + [(900, None, 1), (901, "", 1), (None, "zzbada", 1), (902, "zzbada", 0), (902, "zzbada", 0)]
    docs = spark.createDataFrame(rows, "doc_id int, text string, Score int")
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(400)] + [(5, None), (None, 1), (7000, 1), (8, 1)], "doc_id int, toxic int")
    got = toxicity.classify(docs, labels).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got)
    fold = [r for r in got if r.doc_id is not None and r.doc_id < 400 and zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
    assert np.mean([r.predicted == int(r.doc_id % 4 == 0) for r in fold]) > 0.95
    by = {r.doc_id: r for r in got}
    assert by[None].predicted == 1 and by[900].predicted == 0 and by[900].score == by[901].score
    assert by[902].evidence and by[902].similarity[0] > 0
    none = toxicity.classify(docs, labels.limit(0))
    assert {r.score for r in none.collect()} == {0.0}
    assert toxicity.classify(docs.limit(0), labels).count() == 0


def test_nearest_with_few_dense_rows_equals_all_dense(monkeypatch):
    rng = random.Random(5)
    vectors = [{min(rng.randrange(60), rng.randrange(60)): rng.randint(1, 4) for _ in range(rng.randint(0, 9))} for _ in range(500)]
    whole = toxicity.Index(vectors, 60, block=16)
    monkeypatch.setattr(toxicity, "DENSE", 500 * 4)
    mixed = toxicity.Index(vectors, 60, block=16)
    assert len(mixed.dense) == 4 < len(whole.dense)
    for i, ((a, s), (b, t)) in enumerate(zip(whole.nearest_of(vectors, 7, list(range(500))), mixed.nearest_of(vectors, 7, list(range(500))))):
        assert a.tolist() == b.tolist() and s.tolist() == t.tolist() and i not in a


def test_every_telling_term_is_kept_and_held_out_toxic_texts_are_found(spark):
    rng = random.Random(4)
    plain = lambda: " ".join(rng.choice(["one", "two", "three", "four", "five"]) for _ in range(12))
    bad = [f"{a}{b}zqx{a}{b}" for a in "bcdfghjk" for b in "lmnprstvwz"]
    rows = [(i, f"{plain()} {bad[i // 2 % 80]}" if i % 2 else plain(), i % 2) for i in range(3200)]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id int, text string")
    labels = spark.createDataFrame([(r[0], r[2]) for r in rows], "doc_id int, toxic int")
    model = toxicity.fit(docs, labels, train=~toxicity.held_out(F.col("id")))
    assert set(bad) <= set(model.terms) and len(model.terms) > 256
    fold = toxicity.score(docs.where(toxicity.held_out(F.col("doc_id"))), model).collect()
    toxic = [r.predicted for r in fold if r.doc_id % 2]
    assert len(toxic) > 200 and np.mean(toxic) > 0.98
    assert np.mean([r.predicted for r in fold if not r.doc_id % 2]) < 0.02


def test_language_cases(spark):
    words = {"en": "the house with this that", "de": "das haus mit nicht und", "fr": "les maisons avec être une", "xx": "qqq zzz xxx"}
    rng = random.Random(4)
    rows = [(i, " ".join(rng.choice(words[c].split()) for _ in range(12)), c) for i, c in enumerate(list(words) * 60)]
    rows += [(900, None, "en"), (901, "12 !?", "en"), (902, "das Haus und", None), (None, "the house", "en")]
    docs = spark.createDataFrame(rows, "doc_id int, text string, lang string")
    model = langid.fit(docs, train=~langid.held_out(langid.F.col("doc_id")))
    got = {r.doc_id: r for r in langid.predict(docs, model).collect()}
    assert all(got[i].lang_pred == c for i, _, c in rows if i is not None and i < 900)
    assert (got[900].lang_pred, got[901].lang_pred, got[902].lang_pred, got[None].lang_pred) == ("und", "und", "de", "en")
    assert got[900].score == 0.0 and all(0 <= r.score <= 1 for r in got.values())
    empty = langid.fit(docs.limit(0))
    assert {r.lang_pred for r in langid.predict(docs, empty).collect()} == {"und"}


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the tables")
def test_held_out_accuracy(spark):
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    model = langid.fit(docs.select("doc_id", "text", "lang"), train=~langid.held_out(langid.F.col("doc_id")))
    out = langid.predict(docs, model, keep=["doc_id", "lang"]).where(langid.held_out(langid.F.col("doc_id"))).collect()
    assert len(out) > 100 and np.mean([r.lang == r.lang_pred for r in out]) > 0.97
    scored = toxicity.classify(docs, labels, keep=["doc_id"]).join(labels, "doc_id").where(toxicity.held_out(langid.F.col("doc_id"))).collect()
    clean = [r for r in scored if r.toxic == 0]
    assert len(scored) > 40 and np.mean([r.predicted == 0 for r in clean]) > 0.97


def test_pruned_blocks_are_not_read(monkeypatch):
    rng = random.Random(8)
    monkeypatch.setattr(toxicity, "DENSE", 0)
    vectors = [{rng.randrange(i // 100 * 12, i // 100 * 12 + 14): rng.randint(1, 3) for _ in range(6)} for i in range(2000)]
    index = toxicity.Index(vectors, 300, block=25)
    every = {t: sum(t in v for v in vectors) for t in range(300)}
    few = sum(sum(every[t] for t in v) for v in vectors[::10])
    found = index.nearest_of(vectors[::10], 3)
    assert 0 < index.read < few
    for v, (near, similarity) in zip(vectors[::10], found):
        t, w = index.weigh(v)
        full = [sum(w[list(t).index(x)] * y for x, y in zip(*index.weigh(u)) if x in t) for u in vectors]
        assert np.allclose(similarity, sorted(full, reverse=True)[:3])


def test_score_equals_brute_force(spark):
    rng = random.Random(9)
    word = lambda: "".join(rng.choice("abcd") for _ in range(4))
    rows = [(i, " ".join([word() for _ in range(12)] + [f"zq{rng.choice('xyz')}x"] * (i % 3 == 0))) for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id int, text string")
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(240)], "doc_id int, toxic int")
    model = toxicity.fit(docs, labels, train=~toxicity.held_out(F.col("id")))
    got = {r.doc_id: r for r in toxicity.score(docs, model).collect()}
    # all in plain Python: counts, frequencies over all texts, cosines, votes, isotonic curve
    terms = {t: i for i, t in enumerate(model.terms)}
    def counted(text):
        out = {}
        for w in text.split():
            for t in [w, *("^" + w[:n] for n in (3, 4, 5, 6) if len(w) >= n)]:
                if t in terms:
                    out[t] = out.get(t, 0) + 1
        return out
    counts = {i: counted(t) for i, t in rows}
    df = {t: sum(t in c for c in counts.values()) for t in terms}
    def unit(c):
        v = {t: (1 + np.log(n)) * (np.log((1 + len(rows)) / (1 + df[t])) + 1) for t, n in c.items()}
        size = np.sqrt(sum(x * x for x in v.values()))
        return {t: x / size for t, x in v.items()}
    unit_of = {i: unit(c) for i, c in counts.items()}
    train = [i for i in range(240) if zlib.crc32(str(i).encode()) % 5]
    place = {int(x): n for n, x in enumerate(model.ids)}
    assert set(place) == set(train)
    def vote(v, but=None):
        near = [(sum(x * unit_of[j].get(t, 0) for t, x in v.items()), place[j], j) for j in train if j != but]
        near = sorted((x for x in near if x[0] > 1e-12), key=lambda x: (-round(x[0], 9), x[1]))[: model.k]
        if not near:
            return None
        share = sum(i % 3 == 0 for i in train) / len(train)
        w = [s * s for s, _, _ in near]
        return (sum(x for x, (_, _, j) in zip(w, near) if j % 3 == 0) + 0.05 * share) / (sum(w) + 0.05)
    for i, _ in rows[::7]:
        raw = vote(unit_of[i])
        want = model.bare if raw is None else np.interp(raw, *model.curve)
        assert abs(got[i].score - want) < 1e-6, i
    raw = {i: vote(unit_of[i], i) for i in train}
    known = [i for i in train if raw[i] is not None]
    curve = toxicity.isotonic(np.array([raw[i] for i in known]), np.array([float(i % 3 == 0) for i in known]), np.ones(len(known)))
    assert np.allclose(np.interp([0.1, 0.4, 0.8], *curve), np.interp([0.1, 0.4, 0.8], *model.curve), atol=1e-3)


def test_document_frequencies_cover_all_texts(spark):
    docs = spark.createDataFrame([("a b abc",), ("b",), (None,), ("abcd abcd",)], "text string").repartition(3)
    n, found = toxicity.document_frequencies(docs, ["a", "b", "^abc", "none"])
    assert (n, found.tolist()) == (4, [1, 2, 2, 0])


def plain_language(model, text):
    """Hashed trigrams, margins and votes of a text, one number at a time."""
    import regex

    if not text or not regex.search(r"\p{L}", text):
        return "und"
    b = (" " + " ".join("".join(c if len(c.encode()) > 1 or "a" <= c <= "z" else " " for c in text.lower()).split()) + " ").encode()
    counts, m32 = {}, (1 << 32) - 1
    for x, y, z in zip(b, b[1:], b[2:]):
        h = (x * 0x9E3779B1 + y * 0x85EBCA6B + z * 0xC2B2AE35) & m32
        h = ((h ^ (h >> 15)) * 0x2C1B3C6D & m32) >> 17
        counts[h] = counts.get(h, 0) + 1
    size = sum(counts.values()) ** 0.5
    margin = lambda i: sum(n**0.5 / size * float(model.weights[h, i]) for h, n in counts.items()) + float(model.weights[-1, i])
    family = max(range(len(model.families)), key=margin) if len(model.families) > 1 else 0
    codes = model.members[model.families[family]]
    wins = {c: 0 for c in codes}
    sums = {c: 0.0 for c in codes}
    for a, b, i in model.pairs[model.families[family]]:
        m = margin(i)
        wins[a if m > 0 else b] += 1
        sums[a] += m
        sums[b] -= m
    return min(codes, key=lambda c: (-wins[c], -sums[c], c))


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the tables")
def test_languages_equal_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang")
    model = langid.fit(docs, train=~langid.held_out(F.col("doc_id")))
    got = langid.predict(docs, model).select("text", "lang_pred").collect()
    assert len(got) > 500 and all(plain_language(model, r.text) == r.lang_pred for r in got[::3])


def test_language_empty_and_clashing_tables(spark):
    df = spark.createDataFrame([(1, "the house", "en", "x", "y", "z")], "doc_id int, text string, lang string, Family string, lang_pred string, score string")
    model = langid.fit(df)
    assert langid.predict(df, model).first().lang_pred == "en"
    assert langid.predict(df.limit(0), model).count() == 0 and langid.fit(df, per_language=1).langs in (["en"], [])


def test_language_sample_is_bounded_in_all(spark, monkeypatch):
    monkeypatch.setattr(langid, "TOTAL", 40)
    df = spark.createDataFrame([(i, f"w{i} text", f"l{i % 20}") for i in range(2000)], "doc_id int, text string, lang string")
    rows = []
    own = langid.Model.__init__
    monkeypatch.setattr(langid.Model, "__init__", lambda self, r, langs: rows.append(len(langs)) or own(self, [], []))
    langid.fit(df)
    assert rows[0] <= 80
