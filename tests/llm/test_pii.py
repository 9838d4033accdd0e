import hashlib
import itertools
import random
import re
import time

import numpy as np

from evensort.llm import pii


def plain_base(t):
    found = [(0, *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    found += [(1, *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = [int(c) for c in m[0] if c.isdigit()]
        s = sum(x if i % 2 == 0 else (2 * x if x < 5 else 2 * x - 9) for i, x in enumerate(reversed(d)))
        if 13 <= len(d) <= 19 and s % 10 == 0:
            found.append((2, *m.span()))
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t):
        if 9 <= sum(c in "0123456789" for c in m[0]) <= 15:
            found.append((3, *m.span()))
    return found


def test_base_patterns_equal_plain_search():
    rng = random.Random(1)
    bits = list("aZ09.@-_%+ ()😀é") + ["4111111111111111", "1.2.3.4", "+1 (555) 010-2000", "a@b.c", "@", "..", "255.", "٣"]
    for _ in range(4000):
        t = "".join(rng.choice(bits) for _ in range(rng.randint(0, 25)))
        assert sorted(pii.base_spans(t)) == sorted(plain_base(t)), t


def test_long_runs_are_linear():
    for t in ("a" * 300_000, "1" * 300_000, "a" * 200_000 + "@", "@" * 100_000, "+1" * 100_000, "1." * 100_000):
        pii.base_spans(t)


def graph_and_model(text):
    rng = np.random.default_rng(0)
    g = pii.Graph(text, pii.base_spans(text))
    m = pii.Model()
    m.unary = {f: rng.normal(size=pii.LABELS) for fs in g.features for f in fs}
    m.chain, m.skip = rng.normal(size=(pii.LABELS, pii.LABELS)), np.abs(rng.normal(size=pii.LABELS))
    return g, m


def brute_marginals(g, m):
    own = m.potentials(g)
    n = len(own)
    p = np.zeros((n, pii.LABELS))
    for ys in itertools.product(range(pii.LABELS), repeat=n):
        if any(g.given[i] >= 0 and g.given[i] != y for i, y in enumerate(ys)):
            continue
        s = sum(own[i, y] for i, y in enumerate(ys) if g.given[i] < 0)
        for i in range(n):
            if i not in g.chain:
                s += m.chain[ys[i], pii.OUTSIDE]
            if i - 1 not in g.chain:
                s += m.chain[pii.OUTSIDE, ys[i]]
        # neighbours outside weigh on evidence too, alike in every term
        s += sum(m.chain[ys[i], ys[i + 1]] for i in g.chain) + sum(m.skip[ys[i]] for i, j in g.skip if ys[i] == ys[j])
        for i, y in enumerate(ys):
            p[i, y] += np.exp(s)
    return p / p.sum(axis=1, keepdims=True)


def test_messages_are_exact_on_trees():
    g, m = graph_and_model("x 12 34a 9 word 77 1234567 and 1234567 z")
    assert g.skip and len(g.chain) == 2 + 1
    assert np.abs(pii.Model.marginals(m, g, rounds=200) - brute_marginals(g, m)).max() < 1e-3


def test_repeated_number_takes_its_label():
    texts = [f"call +1 (555) 010-{n} or write to u{n}@mail.example.com about 4{n} items" for n in range(1000, 1060)]
    texts += [f"in {y} they saw {y + 1} and {y * 7}" for y in range(1900, 1960)]
    model = pii.Model().fit([pii.Graph(t, pii.base_spans(t)) for t in texts])
    text = "call +1 (555) 010-1234 now. later call 555 010-1234 again, room 4711"
    added = [text[s:e] for k, s, e, _ in model.added(text, pii.base_spans(text)) if pii.KINDS[k] == "phone"]
    assert "010-1234" in added and not any("4711" in a for a in added)


def test_query_columns(spark):
    texts = [None, "", "mail a.b@c.de and 1.2.3.4", "4111 1111 1111 1111", "+49 (30) 1234567", "no data", "dup a@b.c", "dup a@b.c", "w " * 50_000 + "z@y.x"]
    df = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)], "doc_id int, text string, SPANS int")
    model = pii.fit(df)
    for r in pii.scan(df, model).collect():
        base = sorted(plain_base(texts[r.doc_id] or ""))
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(k == n for k, *_ in base) for n in range(4))
        assert r.base_sha256 == hashlib.sha256(pii.listed(base).encode()).hexdigest()
        assert set(filter(None, pii.listed(base).split(","))) <= set(r.spans.split(","))
    assert pii.scan(df.limit(0), pii.fit(df.limit(0))).count() == 0


def test_long_texts_are_linear():
    model = pii.Model().fit([pii.Graph("call +1 (555) 010-1000 now", pii.base_spans("call +1 (555) 010-1000 now"))])
    for t in ("a" * 1_000_000, "a" * 500_000 + "1", "1a" * 300_000, "@" * 100_000, "4711 " * 20_000, "a1 " * 20_000):
        began = time.perf_counter()
        model.added(t, pii.base_spans(t))
        assert time.perf_counter() - began < 20, t[:20]


def test_evidence_reaches_every_repeat_in_a_document():
    texts = [f"call +1 (555) 010-{n} or write to u{n}@mail.example.com about 4{n} items" for n in range(1000, 1060)]
    model = pii.Model().fit([pii.Graph(t, pii.base_spans(t)) for t in texts])
    model.skip[pii.KINDS.index("phone")] = 6.0
    text = "call +1 (555) 010-1234 now. " + "then later they rang 010-1234 again and again. " * 100
    text = text.replace("010-1234", "0101234")
    added = [text[s:e] for k, s, e, _ in model.added(text, pii.base_spans(text)) if pii.KINDS[k] == "phone"]
    g = pii.Graph(text, pii.base_spans(text))
    p = model.marginals(g)[:, pii.KINDS.index("phone")]
    own = [i for i, (s, e) in enumerate(g.spans) if text[s:e] == "0101234"]
    assert len(own) == 101
    # all repeats without evidence are alike, wherever they stand
    assert np.ptp(p[own[2:]]) < 1e-2 and (not added or added.count("0101234") >= 99)


def test_the_word_behind_is_a_feature():
    g = pii.Graph("Tel: 5550100 (home) 4711 12\nroom", [])
    assert [fs[-1] for fs in g.features] == ["word home", "first 4", "word room"]
    assert pii.Graph("12", []).features[0][-1] == "first 1"


def test_empty_table_and_no_ids(spark):
    df = spark.createDataFrame([], "doc_id int, text string, found string")
    assert pii.scan(df, pii.fit(df)).count() == 0
