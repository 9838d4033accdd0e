"""Language identification by hierarchical discrimination.

Byte trigrams of the lower-cased words are hashed into a unit vector.  One linear SVM for
each language family (against the rest) picks the family; inside it one-versus-one linear
SVMs separate the related languages, and the one with most wins (then the largest summed
margin, then the first name) is the prediction.

SVMs are fitted by dual coordinate descent on a bounded sample of labelled rows
(``per_language`` expected rows, ``TOTAL`` for all together, twice that as a hard bound).

Defined cases: a text that is null or has no letter is ``und`` with score 0; null languages
and null ids aren't learned from; with one language known it is always predicted (score 1);
with none every text is ``und``; repeated rows get equal results; other columns pass.
"""

from __future__ import annotations

import math
import uuid
from itertools import combinations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, DoubleType, StringType, StructField, StructType

from ._arrow import append_columns, checkpoint, column

DIMENSIONS = 1 << 15
PER_LANGUAGE = 1200
#: Sample rows of all languages together; twice that is the hard bound.
TOTAL = 20_000
EPOCHS = 12
COST = 4.0

#: Families of ISO 639-1 codes; any other code is a family of its own.
FAMILIES = {
    "germanic": "en de nl sv da no nb nn is af fy lb yi",
    "romance": "fr es it pt ro ca gl oc la",
    "slavic": "ru uk be pl cs sk sl hr sr bs bg mk",
    "baltic": "lt lv",
    "celtic": "ga gd cy br",
    "uralic": "fi et hu se",
    "turkic": "tr az kk ky uz tk tt",
    "semitic": "ar he mt am",
    "iranian": "fa ku ps tg",
    "indic": "hi bn ur pa gu mr ne si",
    "dravidian": "ta te kn ml",
    "austronesian": "id ms tl jv mg",
}
FAMILY = {code: family for family, codes in FAMILIES.items() for code in codes.split()}

FIELDS = StructType([StructField("lang_pred", StringType()), StructField("family", StringType()), StructField("score", DoubleType())])

#: Everything below 0x80 that is no letter becomes a space.
_LETTERS = bytes(c if c >= 128 or 97 <= c <= 122 else 32 for c in range(256))


def features(text: bytes | None) -> tuple[np.ndarray, np.ndarray] | None:
    """(dimensions, weights) of the unit trigram vector; None without a letter."""
    import regex

    if not text:
        return None
    low = text.decode("utf-8", "replace")
    if not regex.search(r"\p{L}", low):
        return None
    folded = b" " + b" ".join(low.lower().encode().translate(_LETTERS).split()) + b" "
    b = np.frombuffer(folded, np.uint8).astype(np.uint32)
    h = b[:-2] * np.uint32(0x9E3779B1) + b[1:-1] * np.uint32(0x85EBCA6B) + b[2:] * np.uint32(0xC2B2AE35) if len(b) > 2 else b
    h = (h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D) >> np.uint32(17)
    counts = np.bincount(h, minlength=DIMENSIONS)
    at = np.flatnonzero(counts)
    w = np.sqrt(counts[at])
    return at, (w / math.sqrt(float(w @ w))).astype(np.float32)


def fit_svm(rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, cost: float = COST, epochs: int = EPOCHS, seed: int = 1) -> np.ndarray:
    """Weights (last: bias) of a linear SVM with squared hinge loss, classes weighed equally."""
    rng = np.random.default_rng(seed)
    w = np.zeros(DIMENSIONS + 1)
    alpha = np.zeros(len(rows))
    n_pos = max(1, int((y > 0).sum()))
    n_neg = max(1, len(y) - n_pos)
    costs = np.where(y > 0, len(y) / (2 * n_pos), len(y) / (2 * n_neg)) * cost
    for _ in range(epochs):
        moved = 0.0
        for i in rng.permutation(len(rows)):
            at, v = rows[i]
            slope = y[i] * (w[at] @ v + w[-1]) - 1 + alpha[i] / (2 * costs[i])
            now = max(0.0, alpha[i] - slope / (2.0 + 1 / (2 * costs[i])))
            step = (now - alpha[i]) * y[i]
            if step:
                w[at] += step * v
                w[-1] += step
                alpha[i] = now
                moved = max(moved, abs(step))
        if moved < 1e-3:
            break
    return w


class Model:
    def __init__(self, rows: list[tuple[np.ndarray, np.ndarray]], langs: list[str]):
        self.langs = sorted(set(langs))
        own = np.array(langs)
        family = np.array([FAMILY.get(c, c) for c in langs])
        self.families = sorted(set(family.tolist()))
        self.members = {f: [c for c in self.langs if FAMILY.get(c, c) == f] for f in self.families}
        columns: list[np.ndarray] = []
        if len(self.families) > 1:
            columns += [fit_svm(rows, np.where(family == f, 1, -1)) for f in self.families]
        self.pairs: dict[str, list[tuple[str, str, int]]] = {}
        for f, codes in self.members.items():
            self.pairs[f] = []
            for a, b in combinations(codes, 2):
                part = np.flatnonzero((own == a) | (own == b))
                self.pairs[f].append((a, b, len(columns)))
                columns.append(fit_svm([rows[i] for i in part], np.where(own[part] == a, 1, -1)))
        self.weights = np.array(columns, np.float32).T.copy() if columns else np.zeros((DIMENSIONS + 1, 0), np.float32)

    def predict(self, text: bytes | None) -> tuple[str, str | None, float]:
        made = features(text)
        if made is None or not self.langs:
            return "und", None, 0.0
        at, v = made
        margins = v @ self.weights[at] + self.weights[-1]
        sure = 1.0
        family = self.families[0]
        if len(self.families) > 1:
            own = margins[: len(self.families)]
            family = self.families[int(np.argmax(own))]
            best, second = np.sort(own)[-1], np.sort(own)[-2]
            sure *= _logistic(float(best - second))
        codes = self.members[family]
        if len(codes) == 1:
            return codes[0], family, sure
        wins = {c: [0, 0.0] for c in codes}
        for a, b, i in self.pairs[family]:
            m = float(margins[i])
            wins[a if m > 0 else b][0] += 1
            wins[a][1] += m
            wins[b][1] -= m
        lang = min(codes, key=lambda c: (-wins[c][0], -wins[c][1], c))
        weakest = min(float(margins[i]) if a == lang else -float(margins[i]) for a, b, i in self.pairs[family] if lang in (a, b))
        return lang, family, sure * _logistic(weakest)


def _logistic(margin: float, slope: float = 3.0) -> float:
    return 1 / (1 + math.exp(-max(-30.0, min(30.0, slope * margin))))


def held_out(id_col: Column) -> Column:
    """Whether crc32 of the id as text leaves 2 modulo 4; null ids are not held out."""
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", train: Column | None = None, per_language: int = PER_LANGUAGE) -> Model:
    """Fit on a hashed sample of rows with a language where ``train`` holds."""
    known = docs.where(column(lang_col).isNotNull())
    if train is not None:
        known = known.where(train)
    n = {r[0]: r[1] for r in known.groupBy(column(lang_col)).count().collect()}
    if not n:
        return Model([], [])
    per_language = min(per_language, TOTAL / len(n))
    share = F.create_map(*[F.lit(x) for c in n for x in (c, min(1.0, per_language / n[c]))])
    known = known.where(column(text_col).isNotNull())
    dice = F.pmod(F.xxhash64(column(text_col), F.lit(23)), F.lit(1 << 30)) / float(1 << 30)
    sample = known.where(dice < F.element_at(share, column(lang_col))).select(column(lang_col).alias("lang"), column(text_col).alias("text"))
    sample = sample.limit(int(2 * per_language * len(n)))

    def kernel(texts):
        made = [features(t) for t in texts]
        # arrays as bytes: 8 a trigram instead of Python numbers
        return [(None, None) if m is None else (m[0].astype("<i4").tobytes(), m[1].astype("<f4").tobytes()) for m in made]

    fields = StructType([StructField("at", BinaryType()), StructField("v", BinaryType())])
    rows = checkpoint(append_columns(checkpoint(sample), ["text"], lambda: kernel, fields, keep=["lang"])).where("at is not null")
    vectors, langs = [], []
    for r in rows.toLocalIterator():
        vectors.append((np.frombuffer(r["at"], "<i4"), np.frombuffer(r["v"], "<f4")))
        langs.append(r["lang"])
    order = sorted(range(len(langs)), key=lambda i: (langs[i], vectors[i][0].tobytes(), vectors[i][1].tobytes()))
    return Model([vectors[i] for i in order], [langs[i] for i in order])


def predict(docs: DataFrame, model: Model, text_col: str = "text", keep=None) -> DataFrame:
    """``docs`` with lang_pred, family and score."""
    shared = docs.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, model))

    def make():
        own = shared.value[1]
        return lambda texts: [own.predict(t) for t in texts]

    return append_columns(docs, [text_col], make, FIELDS, keep)
