import random
import re

from evensort.llm import decontaminate, mixing

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def plain(t):
    return WORD.findall("".join(c.lower() if c.isascii() else c for c in t or ""))


def brute(text, items):
    own, hit, ids = plain(text), set(), set()
    for i, t in items:
        w = plain(t)
        for s in range(max(1, len(w) - 9) if w else 0):
            p = w[s : s + 10]
            for k in range(len(own) - len(p) + 1):
                if own[k : k + len(p)] == p:
                    hit |= set(range(k, k + len(p)))
                    ids.add(str(i))
    return len(own), len(hit), len(ids), decontaminate.digest(ids), bool(hit)


def cases():
    rng = random.Random(7)
    text = lambda n: " ".join(rng.choice(["a", "B", "ç", "d-e", "f"]) for _ in range(n))
    items = [(1, text(25)), (2, text(3)), (3, None), (4, "..."), (5, text(12)), (1, text(11))]
    docs = [None, "", "!!"] + [text(rng.randint(1, 60)) for _ in range(60)] + ["x " + (items[4][1] or "") + " y"] * 2
    return items, docs


def test_decontamination_equals_brute_force(spark):
    items, docs = cases()
    bench = spark.createDataFrame(items, "item_id int, text string")
    df = spark.createDataFrame([(i, t, "z") for i, t in enumerate(docs)], "doc_id int, text string, N_hit string")
    for r in decontaminate.scan(df, bench).collect():
        assert (r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) == brute(docs[r.doc_id], items)
        raw = (docs[r.doc_id] or "").encode()
        spans = decontaminate.hit_spans(raw, r.hits)
        assert sum(len(plain(raw[s:e].decode())) for s, e in spans) == r.n_hit
    assert decontaminate.scan(df.limit(0), bench).count() == 0
    assert not any(r.contaminated for r in decontaminate.scan(df, bench.limit(0)).collect())


def test_join_way_gives_the_same_pairs(spark):
    items, docs = cases()
    bench = spark.createDataFrame(items, "item_id int, text string")
    df = spark.createDataFrame(list(enumerate(docs)), "doc_id int, text string")
    got = {(r.id, r.item_id) for r in decontaminate.find_by_join(df, bench).collect()}
    want = {(r.doc_id, i) for r in decontaminate.scan(df, bench).collect() for i in r["items"]}
    assert got == want
    try:
        decontaminate.scan(df, bench, max_automaton_words=10)
        raise AssertionError
    except ValueError:
        pass


def test_benchmark_over_the_bound_gives_the_same_rows(spark):
    items, docs = cases()
    items += [(9, " ".join(f"k{i}" for i in range(90))), (10, items[4][1])]
    docs += ["k70 k71 " + " ".join(f"k{i}" for i in range(5, 60)), " ".join(f"k{i}" for i in range(90))]
    bench = spark.createDataFrame(items, "item_id int, text string")
    df = spark.createDataFrame([(i % 50, t, "z") for i, t in enumerate(docs)], "doc_id int, text string, N_hit string")
    rows = lambda d: sorted(map(str, d.collect()))
    want = rows(decontaminate.scan(df, bench))
    for most in (100, 400, 900):
        assert rows(decontaminate.scan(df, bench, max_automaton_words=most)) == want
    assert rows(decontaminate.scan(df, bench, keep=["doc_id"], max_automaton_words=400)) == rows(decontaminate.scan(df, bench, keep=["doc_id"]))


def test_targets_fill_by_weight_under_caps(spark):
    sizes = {"a": 10, "b": 500, "c": 40, "d": 1000, None: 5, "e": 0}
    df = spark.createDataFrame(list(sizes.items()), "source string, size bigint")
    got = {r.source: r.target for r in mixing.source_targets(df).collect()}
    order = sorted((s for s in sizes if s is not None)) + [None]
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    budget, target, open_ = 1.5 * sum(sizes.values()), {}, set(sizes)
    while True:
        left = budget - sum(target.values())
        share = {s: left * weight[s] / sum(weight[x] for x in open_) for s in open_}
        over = {s for s in open_ if share[s] > 2 * sizes[s]}
        if not over:
            target.update(share)
            break
        target.update({s: 2.0 * sizes[s] for s in over})
        open_ -= over
    assert got.keys() == target.keys()
    assert all(abs(got[s] - target[s]) < 1e-6 for s in got)


def test_mix_takes_near_the_target(spark):
    rng = random.Random(8)
    rows = [(i, " ".join(["w"] * rng.randint(0, 60)), rng.choice(["a", "a", "a", "b", None]), 1) for i in range(600)]
    rows += [(None, "x y z", "b", 1), (7, "same row", "a", 1), (7, "same row", "a", 1), (8, None, "b", 1)]
    df = spark.createDataFrame(rows, "doc_id int, text string, source string, size int")
    plan = mixing.plan(df).collect()
    assert len(plan) == len(rows) and max(r.copies for r in plan) <= 2
    for s in {r.source for r in plan}:
        own = [r for r in plan if r.source == s]
        assert sorted(r.rank for r in own) == list(range(1, len(own) + 1))
        assert abs(sum(r.copies * r.size for r in own) - own[0].target) <= 62
    key = lambda p: sorted((str(r.id), str(r.source), r.size, r.copies) for r in p)
    assert key(plan) == key(mixing.plan(df.repartition(7)).collect())
    mixed = mixing.mix(df)
    assert mixed.columns == ["doc_id", "text", "source", "size", "copy"]
    assert mixed.count() == sum(r.copies for r in plan)
    assert mixing.plan(df.limit(0)).count() == 0 and mixing.mix(df.limit(0)).count() == 0


def test_mix_of_clashing_columns(spark):
    rows = [(i, f"w{i} x", "ab"[i % 2], 1, 2, 3, 4, 5) for i in range(40)] + [(3, "w3 x", "b", 1, 2, 3, 4, 5)] * 2
    df = spark.createDataFrame(rows, "id int, hash string, number string, c_id int, copies int, own_id int, size int, __row int")
    out = mixing.mix(df, "id", "hash", "number")
    assert out.columns == [*df.columns, "copy"]
    plan = mixing.plan(df, "id", "hash", "number")
    assert out.count() == sum(r.copies for r in plan.collect()) and out.where("c_id = 1 AND own_id = 3 AND size = 4").count() == out.count()
