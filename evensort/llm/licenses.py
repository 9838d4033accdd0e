"""Licence scans: Aho-Corasick over words finds identifier tags and notice phrases; a
shunting-yard parser evaluates and/or/with licence expressions.

One word automaton holds all phrases and identifiers.  Identifiers that are joined by
``and``, ``or`` or ``with`` (parentheses included) form an expression; it is put into
postfix order by operator precedence (with, and, or: tightest first) and evaluated to a
class: ``or`` takes the most permissive side, ``and`` the most restrictive, ``with`` an
exception that softens its licence by one step.  ``with`` joins a licence to an exception
only.  "or later", "+" and "only" behind an identifier become part of its label.

Defined cases: null or wordless text has no words, no places, empty labels and score 0; a
dangling operator or an unbalanced parenthesis ends the expression at its last complete
part; repeated labels count once; other columns pass through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, DoubleType, LongType, StringType, StructField, StructType

from ._arrow import append_columns
from .words import WordAutomaton, word_offsets, words

#: The base phrases and their labels.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

#: Identifiers as words, their label and restriction (0 public domain ... 4 restricted).
IDENTIFIERS = {
    "mit": ("mit", 1), "mit license": ("mit", 1), "expat license": ("mit", 1), "isc": ("isc", 1), "isc license": ("isc", 1),
    "apache license": ("apache", 1), "apache license version 2 0": ("apache-2.0", 1), "bsd license": ("bsd", 1),
    "zlib": ("zlib", 1), "zlib license": ("zlib", 1), "unlicense": ("unlicense", 0), "cc0": ("cc0", 0), "cc0 1 0": ("cc0", 0), "0bsd": ("0bsd", 0),
    "wtfpl": ("wtfpl", 0), "ncsa": ("ncsa", 1), "postgresql license": ("postgresql", 1), "x11 license": ("x11", 1), "libpng": ("libpng", 1),
    "ms pl": ("ms-pl", 1), "ms rl": ("ms-rl", 2), "boost software license": ("bsl", 1), "openssl license": ("openssl", 1),
    "mozilla public license": ("mpl", 2), "eclipse public license": ("epl", 2), "lesser general public license": ("lgpl", 2),
    "gnu general public license": ("gpl", 3), "affero general public license": ("agpl", 3), "business source license": ("busl", 4),
}
#: Licences with versions, their restriction and versions.
VERSIONED = {
    "apache": (1, "1.0 1.1 2.0"), "bsl": (1, "1.0"), "ecl": (1, "2.0"), "upl": (1, "1.0"), "afl": (1, "2.1 3.0"), "zpl": (1, "2.1"),
    "psf": (1, "2.0"), "php": (1, "3.0 3.01"), "artistic": (1, "1.0 2.0"), "ofl": (1, "1.0 1.1"), "pddl": (0, "1.0"), "mulanpsl": (1, "2.0"),
    "mpl": (2, "1.0 1.1 2.0"), "epl": (2, "1.0 2.0"), "cddl": (2, "1.0 1.1"), "lgpl": (2, "2.0 2.1 3.0"), "odbl": (2, "1.0"),
    "gpl": (3, "1.0 2.0 3.0"), "agpl": (3, "1.0 3.0"), "eupl": (3, "1.1 1.2"), "osl": (3, "2.1 3.0"), "cecill": (3, "2.0 2.1"), "gfdl": (3, "1.1 1.2 1.3"),
    "sspl": (4, "1.0"), "busl": (4, "1.1"), "elastic": (4, "2.0"),
    "cc by": (1, "1.0 2.0 2.5 3.0 4.0"), "cc by sa": (2, "1.0 2.0 2.5 3.0 4.0"), "cc by nc": (4, "1.0 2.0 2.5 3.0 4.0"),
    "cc by nd": (4, "1.0 2.0 2.5 3.0 4.0"), "cc by nc sa": (4, "1.0 2.0 2.5 3.0 4.0"), "cc by nc nd": (4, "1.0 2.0 2.5 3.0 4.0"),
}


def versioned() -> dict[str, tuple[str, int]]:
    """Identifiers of ``VERSIONED``: "gpl 3 0", and for whole versions "gpl v3", "gplv3", "gpl version 3"."""
    out = {}
    for name, (level, versions) in VERSIONED.items():
        for v in versions.split():
            entry = (f"{name.replace(' ', '-')}-{v}", level)
            out[f"{name} {v.replace('.', ' ')}"] = entry
            if v.endswith(".0") and " " not in name:
                out.update({f"{name} v{v[:-2]}": entry, f"{name}v{v[:-2]}": entry, f"{name} version {v[:-2]}": entry, f"{name} v{v[:-2]} 0": entry})
    for clauses in "1234":
        out[f"bsd {clauses} clause"] = (f"bsd-{clauses}-clause", 1)
    return out


#: Identifiers that are words of ordinary prose; they count only in an expression context.
COMMON = {"mit", "isc", "zlib", "unlicense", "cc0", "0bsd"}
EXCEPTIONS = {
    "classpath exception 2 0": "classpath-exception", "classpath exception": "classpath-exception", "llvm exception": "llvm-exception",
    "gcc exception 3 1": "gcc-exception", "autoconf exception 3 0": "autoconf-exception", "bison exception 2 2": "bison-exception",
    "linux syscall note": "linux-syscall-note", "font exception 2 0": "font-exception", "openssl exception": "openssl-exception",
}
#: Notices that say something about a licence without naming one.
NOTICES = {
    "spdx license identifier": "spdx", "public domain": "public-domain", "creative commons": "creative-commons",
    "licensed under": "licensed", "released under the": "licensed", "copyright": "copyright",
}
CONTEXT = {b"license", b"licenses", b"licensed", b"identifier", b"under", b"spdx"}
OPERATORS = {b"or": 1, b"and": 2, b"with": 3}
CLASSES = ("public-domain", "permissive", "weak-copyleft", "copyleft", "restricted")

FIELDS = StructType(
    [
        StructField("n_words", LongType()),
        StructField("n_base", LongType()),
        StructField("first_word", LongType()),
        StructField("last_word", LongType()),
        StructField("base_labels", StringType()),
        StructField("labels", StringType()),
        StructField("score", DoubleType()),
        StructField("expressions", ArrayType(StringType())),
        StructField("license_class", StringType()),
    ]
)


def to_postfix(tokens: list[str | tuple]) -> list:
    """Operands and operators in postfix order; ends at the first token that can't follow.

    Tokens are "(", ")", "or", "and", "with" or operands (tuples).
    """
    out, stack, operand_next = [], [], True
    for t in tokens:
        if t == "(":
            if not operand_next:
                break
            stack.append(t)
        elif t == ")":
            if operand_next or "(" not in stack:
                break
            while stack[-1] != "(":
                out.append(stack.pop())
            stack.pop()
        elif isinstance(t, str):
            if operand_next:
                break
            while stack and stack[-1] != "(" and OPERATORS[stack[-1].encode()] >= OPERATORS[t.encode()]:
                out.append(stack.pop())
            stack.append(t)
            operand_next = True
        else:
            if not operand_next:
                break
            out.append(t)
            operand_next = False
    pending = [t for t in reversed(stack) if t != "("]
    return out + (pending[1:] if operand_next and pending else pending)


def evaluate(postfix: list) -> tuple[str, int] | None:
    """(normal form, restriction) of an expression in postfix order; None if empty."""
    stack: list[tuple[str, int]] = []
    for t in postfix:
        if not isinstance(t, str):
            stack.append(t)
            continue
        if len(stack) < 2:
            break
        right, left = stack.pop(), stack.pop()
        level = {"or": min(left[1], right[1]), "and": max(left[1], right[1]), "with": max(0, left[1] - 1)}[t]
        stack.append((f"({left[0]} {t} {right[0]})", level))
    return stack[-1] if stack else None


def _range_of(own: list[bytes], at: int, label: str, behind: bytes) -> tuple[int, str]:
    """What follows an identifier that ends at word ``at``: "+" or "or later" take later
    versions along, "only" none."""
    if behind.startswith(b"+"):
        return at, f"{label}-or-later"
    following = [w for w in own[at : at + 3]]
    if following[:2] == [b"or", b"later"]:
        return at + 2, f"{label}-or-later"
    if following[:3] in ([b"or", b"any", b"later"], [b"or", b"a", b"later"]):
        return at + 3, f"{label}-or-later"
    if following[:1] == [b"only"]:
        return at + 1, f"{label}-only"
    return at, label


class Scanner:
    def __init__(self):
        self.kinds: dict[tuple[bytes, ...], list[tuple[str, str, int]]] = {}
        for kind, table in (("base", BASE), ("notice", NOTICES), ("exception", EXCEPTIONS)):
            for phrase, label in table.items():
                self.kinds.setdefault(tuple(phrase.encode().split()), []).append((kind, label, 0))
        for phrase, (label, level) in (IDENTIFIERS | versioned()).items():
            self.kinds.setdefault(tuple(phrase.encode().split()), []).append(("id", label, level))
        self.automaton = WordAutomaton(self.kinds)
        self.entries = [(len(p), self.kinds[p]) for p in self.automaton.patterns]

    def __call__(self, text: bytes | None) -> tuple:
        own = words(text)
        hits = self.automaton.scan(own)
        if not hits:
            return len(own), 0, None, None, "", "", 0.0, [], None
        base: list[tuple[int, str]] = []
        labels: set[str] = set()
        atoms: dict[int, tuple[int, tuple[str, int], bool, bool]] = {}
        for end, found in hits:
            for n in found:
                size, entries = self.entries[n]
                start = end + 1 - size
                for kind, label, level in entries:
                    if kind == "base":
                        base.append((start, label))
                    elif kind == "notice":
                        labels.add(label)
                    elif start not in atoms or atoms[start][0] < end + 1:
                        common = size == 1 and own[start].decode() in COMMON
                        atoms[start] = (end + 1, (label, level), common, kind == "exception")
        expressions, levels = self._expressions(text, own, atoms, labels)
        base_labels = {label for _, label in base}
        places = [s for s, _ in base]
        strength = 0.5 * len(base_labels) + 0.8 * len(levels) + 0.2 * len(labels)
        return (
            len(own), len(base), min(places, default=None), max(places, default=None),
            ",".join(sorted(base_labels)), ",".join(sorted(base_labels | labels)), 1 - 0.5**(2 * strength),
            expressions, CLASSES[max(levels)] if levels else None,
        )

    def _expressions(self, text: bytes, own: list[bytes], atoms: dict, labels: set[str]) -> tuple[list[str], list[int]]:
        """Expressions in text order and their restrictions; adds the identifiers' labels."""
        spans, expressions, levels, done = None, [], [], 0
        for start in sorted(atoms):
            # an exception stands behind a licence and "with" only
            if start < done or atoms[start][3]:
                continue
            spans = spans or word_offsets(text)
            gap = lambda i: text[spans[i - 1][1] if i else 0 : spans[i][0] if i < len(own) else len(text)]  # noqa: E731, B023
            tokens, at = [], start
            tokens += ["("] * gap(start).count(b"(")
            while at in atoms:
                at, (label, level), _, excepted = atoms[at]
                if not excepted:
                    at, label = _range_of(own, at, label, gap(at))
                tokens.append((label, level))
                tokens += [")"] * gap(at).split(b"(")[0].count(b")")
                # "with" takes an exception, the others a licence
                if at + 1 < len(own) and own[at] in OPERATORS and at + 1 in atoms and atoms[at + 1][3] == (own[at] == b"with") and not (excepted and own[at] == b"with"):
                    tokens.append(own[at].decode())
                    tokens += ["("] * gap(at + 1).count(b"(")
                    at += 1
                else:
                    break
            operands = [t for t in tokens if not isinstance(t, str)]
            near = CONTEXT.intersection(own[max(0, start - 3) : start] + own[at : at + 1])
            done = at
            if len(operands) == 1 and atoms[start][2] and not near:
                continue
            value = evaluate(to_postfix(tokens))
            if value:
                expressions.append(value[0])
                levels.append(value[1])
                labels.update(o[0] for o in operands)
        return expressions, levels


def scan(docs: DataFrame, text_col: str = "text", keep=None) -> DataFrame:
    """``docs`` with the columns of FIELDS."""

    def make():
        scanner = Scanner()
        return lambda texts: [scanner(t) for t in texts]

    return append_columns(docs, [text_col], make, FIELDS, keep)
