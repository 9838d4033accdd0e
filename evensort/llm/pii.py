"""Personal data: patterns, and a skip-chain conditional random field for repeated mentions.

Base kinds (email, ip, card, phone) are patterns with checks.  The method adds spans:
tokens are labelled by a conditional random field whose chain edges join neighbouring
tokens and whose skip edges join tokens of a document that repeat or resemble each other
(same digits, same last seven digits, same text).  Tokens in base spans are evidence;
loopy message passing carries their labels over the edges, so a number that is phone in one
place is phone where it stands without its context.

A token without digit or "@" can only be outside, which cuts the graph: the messages over
the tokens left are the same as over all.  The word behind a candidate is one of
its features.  Similar tokens are linked to the first of them, so a token that repeats n times
has n - 1 skip edges and evidence at one place reaches all others over two, however long
the document is.  Messages pass until none moves by ``SETTLED``, or ``ROUNDS`` times, which
only loops that don't settle reach.

Weights are fitted by pseudo-likelihood on a bounded sample of texts (``rows`` expected,
twice that as a hard bound) labelled by the base patterns.

Defined cases: null text is empty and has no spans; without a sample that has personal data
all weights are zero and nothing is added; repeated rows are independent; texts of any
length are read whole, in time linear in their length; other columns pass.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections import Counter
from itertools import pairwise

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StringType, StructField, StructType

from ._arrow import append_columns, checkpoint, column

KINDS = ("email", "ip", "card", "phone")
OUTSIDE = len(KINDS)
LABELS = len(KINDS) + 1
FIT_ROWS = 3000
EPOCHS = 8
ROUNDS = 200
SETTLED = 1e-3
LEAST = 0.6
#: Sample tokens that a context feature must stand at to be learned.
LEAST_SEEN = 5

_LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# a match can't start inside a run of digits: the run's start would match or fail alike
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_RUN = re.compile(r"\S+")
_CANDIDATE = re.compile(r"[0-9@]")
_EDGE = ".,;:!?()[]{}<>\"'"
_DIGITS = re.compile(r"[^0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost addresses, found from each "@" outwards, so in linear time."""
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL_CHARS:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        free = m.end() if m else at + 1
        if m:
            out.append((start, m.end()))
        at = text.find("@", free)
    return out


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind number, start, end) of the base patterns."""
    found = [(0, s, e) for s, e in emails(text)]
    found += [(1, *m.span()) for m in _IP.finditer(text) if all(len(p.lstrip("0")) < 4 and int(p) <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 13 <= len(digits) <= 19 and luhn(digits):
            found.append((2, *m.span()))
    if "+" in text:
        found += [(3, *m.span()) for m in _PHONE.finditer(text) if 9 <= sum(c.isdigit() for c in m[0]) <= 15]
    return found


def shape(token: str) -> str:
    """Runs of digits, letters and other signs, each once."""
    classes = ["9" if c.isdigit() else "a" if c.isalpha() else c for c in token]
    return "".join(c for i, c in enumerate(classes) if i == 0 or c != classes[i - 1])[:12]


def similar_keys(token: str) -> list[str]:
    """Keys that similar tokens share; a token is linked to the first one with the same key."""
    if "@" in token:
        return [token.strip(_EDGE).lower()]
    digits = _DIGITS.sub("", token)
    if len(digits) >= 7:
        return [digits, "~" + digits[-7:]] if len(digits) > 7 else ["~" + digits]
    return [token] if len(digits) >= 4 else []


def _context(word: str) -> str:
    """The word behind a candidate as a feature; empty if it is a candidate itself."""
    return "" if _CANDIDATE.search(word) else word[:40].strip(_EDGE).lower()[:20]


class Graph:
    """Candidate tokens of a text, their features, evidence, chain and skip edges."""

    def __init__(self, text: str, base: list[tuple[int, int, int]]):
        tokens, behind = [], []
        for m in _RUN.finditer(text):
            if len(behind) < len(tokens):
                behind.append(_context(m[0]))
            if _CANDIDATE.search(m[0]):
                tokens.append((m[0], m.start(), m.end()))
        behind += [""] * (len(tokens) - len(behind))
        self.spans = [(s, e) for _, s, e in tokens]
        self.given = np.full(len(tokens), -1)
        spans, at = sorted(base, key=lambda x: (x[1], x[0])), 0
        for i, (_, s, e) in enumerate(tokens):
            while at < len(spans) and spans[at][2] <= s:
                at += 1
            for kind, b, f in spans[at : at + 4]:
                if b < e and s < f and self.given[i] < 0:
                    self.given[i] = kind
        self.chain = [i for i, (a, b) in enumerate(pairwise(self.spans)) if not text[a[1] : b[0]].strip()]
        first: dict[str, int] = {}
        pairs: dict[tuple[int, int], None] = {}
        for i, (t, _, _) in enumerate(tokens):
            for key in similar_keys(t):
                if first.setdefault(key, i) != i:
                    pairs[first[key], i] = None
        self.skip = list(pairs)
        self.features = [self._features(t) + ([f"word {w}"] if w else []) for (t, _, _), w in zip(tokens, behind)]

    @staticmethod
    def _features(token: str) -> list[str]:
        digits = sum(c.isdigit() for c in token)
        return ["bias", f"shape {shape(token)}", f"digits {min(digits, 20)}", f"at {'@' in token}", f"dots {min(token.count('.'), 4)}", f"first {token[0]}"]


class Model:
    def __init__(self):
        self.unary: dict[str, np.ndarray] = {}
        self.chain = np.zeros((LABELS, LABELS))
        self.skip = np.zeros(LABELS)

    def potentials(self, g: Graph) -> np.ndarray:
        zero = np.zeros(LABELS)
        return np.array([sum((self.unary.get(f, zero) for f in fs), zero) for fs in g.features]).reshape(-1, LABELS)

    def fit(self, graphs: list[Graph], epochs: int = EPOCHS, rate: float = 0.2, decay: float = 1e-4) -> Model:
        """Stochastic ascent of the pseudo-likelihood; unlabelled candidates are outside."""
        rng = np.random.default_rng(1)
        seen = Counter(f for g in graphs for fs in g.features for f in fs)
        known = lambda f: seen[f] >= LEAST_SEEN or not f.startswith("word ")
        learned = [[[f for f in fs if known(f)] for fs in g.features] for g in graphs]
        for epoch in range(epochs):
            step = rate / (1 + epoch)
            for n in rng.permutation(len(graphs)):
                g = graphs[n]
                y = np.where(g.given >= 0, g.given, OUTSIDE)
                before, after, alike = _neighbours(g)
                for i, fs in enumerate(learned[n]):
                    score = sum(self.unary.get(f, 0) for f in fs) + np.zeros(LABELS)
                    left = y[before[i]] if before[i] >= 0 else OUTSIDE
                    right = y[after[i]] if after[i] >= 0 else OUTSIDE
                    score = score + self.chain[left] + self.chain[:, right]
                    for j in alike[i]:
                        score[y[j]] += self.skip[y[j]]
                    p = np.exp(score - score.max())
                    slope = -p / p.sum()
                    slope[y[i]] += 1
                    for f in fs:
                        self.unary[f] = self.unary.get(f, np.zeros(LABELS)) * (1 - decay) + step * slope
                    self.chain[left] += step * slope
                    self.chain[:, right] += step * slope
                    for j in alike[i]:
                        self.skip[y[j]] += step * slope[y[j]]
        # similar tokens never repel
        self.skip = np.clip(self.skip, 0, 6)
        return self

    def marginals(self, g: Graph, rounds: int = ROUNDS) -> np.ndarray:
        """Label probabilities of each candidate by loopy message passing with evidence."""
        own = self.potentials(g)
        before, after, _ = _neighbours(g)
        own[before < 0] += self.chain[OUTSIDE]
        own[after < 0] += self.chain[:, OUTSIDE]
        own[g.given >= 0] = -1e9
        own[np.flatnonzero(g.given >= 0), g.given[g.given >= 0]] = 0
        pairs = [(i, i + 1) for i in g.chain] + g.skip
        if not pairs:
            return _normal(own)
        a, b = np.array(pairs).T
        tables = np.empty((len(pairs), LABELS, LABELS))
        tables[: len(g.chain)] = self.chain
        tables[len(g.chain) :] = np.diag(self.skip)
        source, target = np.r_[a, b], np.r_[b, a]
        table = np.concatenate([tables, tables.transpose(0, 2, 1)])
        back = np.r_[len(pairs) : 2 * len(pairs), 0 : len(pairs)]
        messages = np.zeros((2 * len(pairs), LABELS))
        for _ in range(rounds):
            total = own.copy()
            np.add.at(total, target, messages)
            incoming = (total[source] - messages[back])[:, :, None] + table
            top = incoming.max(axis=1, keepdims=True)
            new = np.log(np.exp(incoming - top).sum(axis=1)) + top[:, 0]
            new -= new.max(axis=1, keepdims=True)
            moved = np.abs(new - messages).max()
            messages = 0.5 * messages + 0.5 * new
            if moved < SETTLED:
                break
        total = own.copy()
        np.add.at(total, target, messages)
        return _normal(total)

    def added(self, text: str, base: list[tuple[int, int, int]], least: float = LEAST) -> list[tuple[int, int, int, float]]:
        """(kind, start, end, probability) of spans beyond the base ones."""
        if not self.unary:
            return []
        g = Graph(text, base)
        if not len(g.given) or (g.given >= 0).all():
            return []
        p = self.marginals(g)
        joined = set(g.chain)
        out: list[list] = []
        last = -2
        for i in np.flatnonzero(g.given < 0).tolist():
            kind = int(p[i].argmax())
            if kind == OUTSIDE or p[i, kind] < least:
                continue
            s, e = g.spans[i]
            if last == i - 1 and last in joined and out[-1][0] == kind:
                out[-1][2], out[-1][3] = e, min(out[-1][3], float(p[i, kind]))
            else:
                out.append([kind, s, e, float(p[i, kind])])
            last = i
        made = []
        for kind, s, e, sure in out:
            while s < e and text[s] in _EDGE:
                s += 1
            while e > s and text[e - 1] in _EDGE:
                e -= 1
            if s < e:
                made.append((kind, s, e, sure))
        return made


def _normal(scores: np.ndarray) -> np.ndarray:
    p = np.exp(scores - scores.max(axis=1, keepdims=True))
    return p / p.sum(axis=1, keepdims=True)


def _neighbours(g: Graph) -> tuple[np.ndarray, np.ndarray, list[list[int]]]:
    n = len(g.features)
    before, after, alike = np.full(n, -1), np.full(n, -1), [[] for _ in range(n)]
    for i in g.chain:
        before[i + 1], after[i] = i, i + 1
    for i, j in g.skip:
        alike[i].append(j)
        alike[j].append(i)
    return before, after, alike


def listed(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for k, s, e in sorted(spans))


FIELDS = StructType(
    [
        *[StructField(f"n_{k}", LongType()) for k in KINDS],
        StructField("base_sha256", StringType()),
        StructField("spans", StringType()),
        StructField(
            "found",
            ArrayType(
                StructType(
                    [StructField("kind", StringType()), StructField("start", LongType()), StructField("end", LongType()), StructField("probability", DoubleType())]
                )
            ),
        ),
    ]
)


def fit(docs: DataFrame, text_col: str = "text", rows: int = FIT_ROWS) -> Model:
    """Fit on a hashed sample of texts that have a digit or "@"."""
    own = docs.where(column(text_col).rlike("[0-9@]")).select(column(text_col).alias("text"))
    n = own.count()
    dice = F.pmod(F.xxhash64("text", F.lit(29)), F.lit(1 << 30)) / float(1 << 30)
    sample = checkpoint(own.where(dice < min(1.0, rows / max(1, n))).limit(2 * rows))
    graphs = []
    for r in sample.toLocalIterator():
        g = Graph(r.text, base_spans(r.text))
        if len(g.given):
            graphs.append((r.text, g))
    graphs = [g for _, g in sorted(graphs, key=lambda x: x[0])]
    if not any((g.given >= 0).any() for g in graphs):
        return Model()
    return Model().fit(graphs)


def scan(docs: DataFrame, model: Model, text_col: str = "text", keep=None) -> DataFrame:
    """``docs`` with counts of the base kinds, base_sha256, spans (text) and found."""
    shared = docs.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, model))
    candidate = re.compile(rb"[0-9@]")
    nothing = (0, 0, 0, 0, hashlib.sha256(b"").hexdigest(), "", [])

    def make():
        own = shared.value[1]

        def one(raw):
            if not raw or not candidate.search(raw):
                return nothing
            text = raw.decode("utf-8", "replace")
            base = base_spans(text)
            more = own.added(text, base)
            counts = [sum(k == n for k, *_ in base) for n in range(len(KINDS))]
            every = base + [m[:3] for m in more]
            found = [(KINDS[k], s, e, 1.0) for k, s, e in sorted(base)] + [(KINDS[k], s, e, p) for k, s, e, p in more]
            return (*counts, hashlib.sha256(listed(base).encode()).hexdigest(), listed(every), found)

        return lambda texts: [one(t) for t in texts]

    return append_columns(docs, [text_col], make, FIELDS, keep)
