import random
import re

from evensort.llm import licenses
from evensort.llm.words import WordAutomaton, word_offsets, words

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def plain_words(t):
    return WORD.findall("".join(c.lower() if c.isascii() else c for c in t or ""))


def test_words_fold_ascii_only():
    t = "Ünïcode ÄB cd-EF_3\x00x"
    assert [w.decode() for w in words(t.encode())] == plain_words(t)
    raw = t.encode()
    assert [raw[s:e].lower() for s, e in word_offsets(raw)] == [w for w in words(raw)]


def test_automaton_equals_search():
    rng = random.Random(5)
    patterns = {tuple(rng.choice([b"a", b"b", b"c"]) for _ in range(rng.randint(1, 5))) for _ in range(30)}
    auto = WordAutomaton(patterns)
    for _ in range(200):
        text = [rng.choice([b"a", b"b", b"c", b"z"]) for _ in range(rng.randint(0, 30))]
        got = sorted((e, auto.patterns[n]) for e, ns in auto.scan(text) for n in ns)
        want = sorted((i + len(p) - 1, p) for p in patterns for i in range(len(text)) if tuple(text[i : i + len(p)]) == p)
        assert got == want


def test_shunting_yard():
    a, b, c = ("a", 1), ("b", 3), ("c", 4)
    assert licenses.to_postfix([a, "or", b, "and", c]) == [a, b, c, "and", "or"]
    assert licenses.to_postfix(["(", a, "or", b, ")", "and", c]) == [a, b, "or", c, "and"]
    assert licenses.evaluate(licenses.to_postfix([a, "or", b, "and", c])) == ("(a or (b and c))", 1)
    assert licenses.evaluate(licenses.to_postfix([b, "with", a, "and", a])) == ("((b with a) and a)", 2)
    assert licenses.evaluate(licenses.to_postfix([a, "or"])) == ("a", 1)
    assert licenses.evaluate(licenses.to_postfix([")"])) is None


def test_base_columns_equal_search(spark):
    rng = random.Random(6)
    bits = ["CC", "by", "General Public", "License", "All rights", "reserved", "the", "CC-BY", "MIT or Apache-2.0", "SPDX-License-Identifier: (GPL-2.0 WITH Classpath-exception-2.0) OR MIT"]
    texts = [None, "", "..."] + [" ".join(rng.choice(bits) for _ in range(rng.randint(1, 15))) for _ in range(150)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")
    for r in licenses.scan(df).collect():
        w = plain_words(texts[r.doc_id])
        places = [(i, label) for p, label in licenses.BASE.items() for i in range(len(w)) if w[i : i + len(p.split())] == p.split()]
        assert (r.n_words, r.n_base) == (len(w), len(places))
        assert (r.first_word, r.last_word) == (min((i for i, _ in places), default=None), max((i for i, _ in places), default=None))
        assert r.base_labels == ",".join(sorted({label for _, label in places}))
        assert set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(","))
        assert 0 <= r.score <= 1


def test_expressions():
    scan = licenses.Scanner()
    r = scan(b"SPDX-License-Identifier: (GPL-2.0 WITH Classpath-exception-2.0) OR MIT")
    assert r[7] == ["((gpl-2.0 with classpath-exception) or mit)"] or r[7] == ["((gpl-2.0 with classpath-exception-2.0) or mit)"]
    assert scan(b"Released under the MIT License.")[5] == "licensed,mit"
    assert scan(b"Licensed under CC BY-NC 4.0.")[4] == "cc-by"
    assert "mit" not in scan(b"das kommt mit dem Wagen")[5]


def test_ranges_of_versions_and_exceptions():
    scan = licenses.Scanner()
    told = lambda t: scan(t.encode())[7]
    assert told("SPDX-License-Identifier: GPL-2.0-or-later") == ["gpl-2.0-or-later"]
    assert told("SPDX-License-Identifier: GPL-2.0-only OR MIT") == ["(gpl-2.0-only or mit)"]
    assert told("License: GPL-2.0+ WITH Classpath-exception-2.0 AND LGPL-3.0+") == ["((gpl-2.0-or-later with classpath-exception) and lgpl-3.0-or-later)"]
    assert told("licensed under GPLv3 or any later version") == ["gpl-3.0-or-later"]
    # "with" takes no licence, and an exception needs one in front
    assert told("License: Apache-2.0 WITH MIT license") == ["apache-2.0", "mit"]
    assert told("see the LLVM exception") == []
    assert told("License: MIT OR LLVM-exception") == ["mit"]
    assert told("License: (MPL-1.1 OR EUPL-1.2) AND CC-BY-NC-SA-3.0") == ["((mpl-1.1 or eupl-1.2) and cc-by-nc-sa-3.0)"]
    assert scan(b"License: (MPL-1.1 OR EUPL-1.2) AND CC-BY-NC-SA-3.0")[8] == "restricted"


def test_empty_and_clashing_tables(spark):
    df = spark.createDataFrame([(1, "MIT License", 5, "x")], "doc_id int, text string, Labels int, expressions string")
    assert licenses.scan(df).first().labels == "mit"
    assert licenses.scan(df).columns[:2] == ["doc_id", "text"] and licenses.scan(df.limit(0)).count() == 0
