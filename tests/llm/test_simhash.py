import random

import numpy as np
import xxhash

from evensort.llm import simhash


def brute_fp(text, size=4):
    own = (text or "").encode().lower().split()
    if not own:
        return 0
    grams = [own[i : i + size] for i in range(max(1, len(own) - size + 1))]
    hashes = [xxhash.xxh64_intdigest(b" ".join(g), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(codes, threshold=4):
    codes = sorted(set(codes))
    parent = {c: c for c in codes}

    def find(c):
        while parent[c] != c:
            c = parent[c]
        return c

    for i, a in enumerate(codes):
        for b in codes[:i]:
            if (a ^ b).bit_count() <= threshold:
                parent[max(find(a), find(b))] = min(find(a), find(b))
    return {c: find(c) for c in codes}


def clouds(rng, groups=40, size=30):
    out = []
    for _ in range(groups):
        c = rng.getrandbits(64)
        for _ in range(rng.randint(1, size)):
            out.append(c)
            for _ in range(rng.randint(0, 4)):
                c ^= 1 << rng.randrange(64)
    return list(dict.fromkeys(out))


def test_fingerprint_is_the_majority():
    rng = random.Random(1)
    for t in [None, "", " \t", "One", "a b c", "A b c D", "x\x0by z\x1cq w"] + [" ".join(rng.choice("abc") for _ in range(n)) for n in range(4, 80)]:
        assert simhash.fingerprint(simhash.shingle_hashes(t.encode() if t is not None else None)) == brute_fp(t)


def test_tree_finds_all_within_threshold():
    rng = random.Random(2)
    codes = np.array(clouds(rng, 60, 40), np.uint64)
    tree = simhash.GrayTree(codes)
    alive = np.ones(len(codes), bool)
    for c in codes[::7]:
        near = {int(tree.codes[i]) for i in tree.within(c, 4, alive)}
        assert near == {int(x) for x in codes if (int(x) ^ int(c)).bit_count() <= 4}


def test_spanning_links_of_dense_and_sparse_buckets():
    rng = random.Random(9)
    base = rng.getrandbits(64)
    dense = list({base ^ sum(1 << b for b in rng.sample(range(30), rng.randint(0, 3))) for _ in range(1500)})
    for codes in (dense, clouds(rng), dense + clouds(rng), [5], [5, 1 << 40]):
        made = simhash.spanning_links(np.array(codes, np.uint64), 4)
        parent = list(range(len(codes)))

        def find(x):
            while parent[x] != x:
                x = parent[x]
            return x

        for a, b in made:
            assert (codes[a] ^ codes[b]).bit_count() <= 4 and find(a) != find(b)
            parent[find(a)] = find(b)
        want = brute_components(codes)
        assert len(made) == len(codes) - len(set(want.values()))


def test_gray_rank_inverts_gray_code():
    n = np.arange(5000, dtype=np.uint64)
    assert (simhash.gray_rank(n ^ (n >> np.uint64(1))) == n).all()


def test_components_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(simhash, "LEAF", 8)
    rng = random.Random(3)
    codes = clouds(rng)
    signed = [(c - (1 << 64) if c >> 63 else c,) for c in codes]
    df = spark.createDataFrame(signed, "fp long")
    got = {r.node % (1 << 64): r.root % (1 << 64) for r in simhash.components(simhash.links(df)).collect()}
    want = brute_components(codes)
    classes = lambda m: {frozenset(c for c in m if m[c] == r) for r in set(m.values())}
    assert classes({c: got.get(c, c) for c in codes}) == classes(want)


def test_rows_nulls_repeats_and_dedup(spark):
    long = " ".join(f"w{i}" for i in range(200))
    rows = [(5, "a b c d e", 0), (3, "A  b c d e", 1), (9, None, 2), (7, " ", 3), (None, long, 4), (11, long, 5), (12, "other words stand here", 6), (12, "other words stand here", 7)]
    df = spark.createDataFrame(rows, "doc_id int, text string, __FP2 int")
    got = sorted((r.doc_id or -1, r.component_id) for r in simhash.near_duplicates(df).collect())
    assert got == [(-1, 11), (3, 3), (5, 3), (7, 7), (9, 7), (11, 11), (12, 12), (12, 12)]
    kept = simhash.deduplicate(df)
    assert kept.columns == df.columns
    assert sorted(r.doc_id for r in kept.collect()) == [3, 7, 11, 12]
    assert simhash.near_duplicates(df.limit(0)).count() == 0
    assert simhash.deduplicate(df.limit(0)).count() == 0


def test_components_equal_brute_force_through_the_index(spark, monkeypatch):
    entered = []
    own = simhash.GrayForest.within
    monkeypatch.setattr(simhash.GrayForest, "within", lambda self, *a: entered.append(len(self.levels)) or own(self, *a))
    rng = random.Random(12)
    base = rng.getrandbits(64)
    dense = {base ^ sum(1 << b for b in rng.sample(range(20), rng.randint(0, 3))) for _ in range(3000)}
    codes = np.array(list(dense | set(clouds(rng, 80, 20))), np.uint64)
    found = simhash.bucket_links(codes, np.zeros(len(codes), np.int64), 4)
    want = brute_components(codes.tolist())
    assert max(entered) >= 3 and len(found[0]) == len(codes) - len(set(want.values()))
    made = spark.createDataFrame([(int(a.view(np.int64)), int(b.view(np.int64))) for a, b in zip(*found)], "a long, b long")
    got = {r.node % (1 << 64): r.root % (1 << 64) for r in simhash.components(made).collect()}
    classes = lambda m: {frozenset(c for c in m if m[c] == r) for r in set(m.values())}
    assert classes({c: got.get(c, c) for c in want}) == classes(want)


def test_hot_buckets_are_cut_without_loss(spark):
    rng = random.Random(13)
    codes = clouds(rng, 60, 20)
    hot = rng.getrandbits(13)
    codes = list(dict.fromkeys(codes + [(c >> 13 << 13) | hot for c in codes]))
    df = spark.createDataFrame([(c - (1 << 64) if c >> 63 else c,) for c in codes], "fp long")
    plain, cut = (simhash.links(df, hot=n).collect() for n in (10**6, 30))
    def roots(rows):
        parent = {c: c for c in codes}
        def find(x):
            while parent[x] != x:
                x = parent[x]
            return x
        for r in rows:
            a, b = r.a % (1 << 64), r.b % (1 << 64)
            assert (a ^ b).bit_count() <= 4
            parent[max(find(a), find(b))] = min(find(a), find(b))
        return {c: find(c) for c in codes}
    want = brute_components(codes)
    assert roots(plain) == roots(cut) == want


def test_batches_over_the_bound_are_cut(monkeypatch):
    rng = random.Random(14)
    base = rng.getrandbits(64)
    codes = np.array(list({base ^ sum(1 << b for b in rng.sample(range(24), rng.randint(0, 2))) for _ in range(900)}), np.uint64)
    whole = len(simhash.bucket_links(codes, np.zeros(len(codes)), 4)[0])
    monkeypatch.setattr(simhash, "NODES", 500)
    assert len(simhash.bucket_links(codes, np.zeros(len(codes)), 4)[0]) == whole == len(codes) - 1


def test_clashing_columns_of_dedup(spark):
    rows = [(1, "a b c d", 5, "x", 1, 2), (2, "A b c d", 5, "x", 1, 2), (2, "z y", 5, "y", 1, 2), (None, None, None, None, None, None)]
    df = spark.createDataFrame(rows, "fp int, i string, component_id int, __row string, stay_id int, __id int")
    kept = simhash.deduplicate(df, "fp", "i")
    assert kept.columns == df.columns and sorted(str(r.fp) for r in kept.collect()) == ["1", "2", "None"]
    assert simhash.near_duplicates(df, "fp", "i").columns == ["fp", "__fp", "component_id"]
