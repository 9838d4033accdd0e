"""Secret scans in DataFrame functions only: patterns and sliding-window entropy.

Base kinds (assign, access, hex) are patterns; spans are code points, end exclusive.  The
method adds spans of kind ``entropy``: candidate strings are runs of one character class
(hex digits, alphanumerics, base64); over each a window slides one character at a time and
the Shannon entropy of its contents is kept by counts: a step changes only the count of the
character that leaves and of the one that enters, so the sum of c*log2(c) is updated by
those two terms.  A candidate is reported, from the first to the last window at or over its
class's threshold, unless it lacks a digit or a letter, it
matches the allow list anywhere, or it overlaps a base span.

Positions without a position function: ``split`` gives the text between matches, so a
match starts at the summed lengths of the gaps and matches before it.

Defined cases: null text is empty and has no spans; repeated rows and ids are independent;
overlapping classes report one span each candidate start (the first class listed); texts of
any length work in one row; other columns pass through unless they carry an output's name.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._arrow import column, without

#: The base patterns.
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST = 6, 20, 24

#: Kinds in listed order; the digests sort by start, then by this order.
KINDS = ("assign", "access", "hex", "entropy")

#: Window length, and for each class its characters and the least entropy in bits.
WINDOW = 20
CLASSES = (("hex", "0-9A-Fa-f", 3.0), ("alnum", "A-Za-z0-9", 3.6), ("base64", "A-Za-z0-9+/_=-", 3.8))
#: A candidate that matches is no secret: UUIDs, sample values, plain words, numbers, paths of words.
ALLOW = r"(?i)^[0-9a-f]{8}(-[0-9a-f]{4}){3}-[0-9a-f]{12}$|example|sample|dummy|placeholder|changeme|^[a-z/_-]+$|^[0-9-]+$|(.)\2{7,}"

OUTPUTS = ("n_assign", "n_access", "n_hex", "n_entropy", "base_sha256", "spans", "found")


#: Matches whose places are added up in one fold; a fold copies its list at every step.
CHUNK = 256
#: Bits of a long that hold counts.
LONG_BITS = 63


def _matches(text: str, pattern: str) -> str:
    """SQL: array<struct<s, e, m>> of the leftmost non-overlapping matches of a pattern.

    Places are summed inside chunks of ``CHUNK`` matches, then chunks are shifted by the sums
    of those before, so that a text of many matches isn't quadratic in them."""
    quoted = "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"
    pairs = f"zip_with(regexp_extract_all({text}, {quoted}, 0), split({text}, {quoted}, -1), (a, b) -> struct(a AS m, b AS g))"
    found = "array<struct<s: int, e: int, m: string>>"
    chunk = f"""aggregate(slice(found, c * {CHUNK} + 1, {CHUNK}), struct(0 AS at, cast(array() AS {found}) AS out),
        (acc, x) -> struct(acc.at + char_length(x.g) + char_length(x.m) AS at,
            concat(acc.out, array(struct(acc.at + char_length(x.g) AS s,
                acc.at + char_length(x.g) + char_length(x.m) AS e, x.m AS m))) AS out))"""
    chunks = f"transform(sequence(0, (size(found) - 1) div {CHUNK}), c -> {chunk})"
    starts = "aggregate(chunks, struct(0 AS at, cast(array() AS array<int>) AS out), (acc, c) -> struct(acc.at + c.at AS at, concat(acc.out, array(acc.at)) AS out), acc -> acc.out)"
    moved = "flatten(zip_with(chunks, starts, (c, at) -> transform(c.out, x -> struct(x.s + at AS s, x.e + at AS e, x.m AS m))))"
    placed = f"transform(array({chunks}), chunks -> transform(array({starts}), starts -> {moved})[0])[0]"
    return f"""transform(array(filter({pairs}, x -> x.m IS NOT NULL)), found ->
        IF(size(found) = 0, cast(array() AS {found}), {placed}))[0]"""


def _entropy(value: str, symbols: str, window: int, least: float) -> str:
    """SQL: struct<s, e> of the windows of a string at or over a threshold; null if none.

    The string is split into characters once.  The fold's state has the window's counts,
    packed into as few longs as hold them, the sum of c*log2(c), the place, the first and
    the last hit.  A step takes one from the count of the character that leaves, adds one to
    that of the character that enters, and moves the sum by those two terms."""
    # entropy = log2(w) - sum / w >= least
    most = window * (math.log2(window) - least) + 1e-9
    bits = window.bit_length()
    fields = LONG_BITS // bits
    longs = range(-(-len(symbols) // fields))
    terms = [n * math.log2(n) if n else 0.0 for n in range(window + 1)]
    gain = "array(0D, " + ", ".join(f"{b - a!r}D" for a, b in zip(terms, terms[1:])) + ")"
    codes = f"""transform(split({value}, ''), ch -> transform(array(instr('{symbols}', ch) - 1), n ->
        struct(n div {fields} AS k, shiftleft(1L, cast({bits} * (n % {fields}) AS int)) AS one, cast({bits} * (n % {fields}) AS int) AS at))[0])"""
    count = lambda x: f"cast(shiftright(CASE {x}.k " + " ".join(f"WHEN {k} THEN a.c{k}" for k in longs) + f" END, {x}.at) & {(1 << bits) - 1} AS int)"
    zero = "struct(" + ", ".join(f"0L AS c{k}" for k in longs) + ", 0D AS sum)"
    entered = ", ".join(f"IF(x.k = {k}, a.c{k} + x.one, a.c{k}) AS c{k}" for k in longs)
    first = f"aggregate(slice(codes, 1, {window}), {zero}, (a, x) -> struct({entered}, a.sum + {gain}[{count('x')} + 1] AS sum))"
    hit = lambda s: f"{s} <= {most!r}D"
    start = f"""transform(array({first}), f -> struct({", ".join(f"f.c{k} AS c{k}" for k in longs)}, f.sum AS sum, 1 AS at,
        IF({hit("f.sum")}, 1, 0) AS lo, IF({hit("f.sum")}, 1, 0) AS hi))[0]"""
    moved = ", ".join(f"IF(x.o.k = {k}, IF(x.i.k = {k}, a.c{k} - x.o.one + x.i.one, a.c{k} - x.o.one), IF(x.i.k = {k}, a.c{k} + x.i.one, a.c{k})) AS c{k}" for k in longs)
    # the same character leaving and entering changes nothing
    summed = f"IF(x.o.k = x.i.k AND x.o.at = x.i.at, a.sum, a.sum - {gain}[{count('x.o')}] + {gain}[{count('x.i')} + 1])"
    step = f"""transform(array({summed}), s -> struct({moved}, s AS sum, a.at + 1 AS at,
        IF(a.lo = 0 AND {hit("s")}, a.at + 1, a.lo) AS lo, IF({hit("s")}, a.at + 1, a.hi) AS hi))[0]"""
    steps = f"zip_with(slice(codes, 1, size(codes) - {window}), slice(codes, {window + 1}, size(codes) - {window}), (o, i) -> struct(o AS o, i AS i))"
    return f"""transform(array({codes}), codes -> aggregate({steps}, {start}, (a, x) -> {step},
        a -> IF(a.lo = 0, NULL, struct(a.lo AS lo, a.hi + {window - 1} AS hi))))[0]"""


def _symbols(chars: str) -> str:
    """The characters of a bracket expression (ranges and single ones)."""
    return "".join(c for c in map(chr, range(33, 127)) if re.fullmatch(f"[{chars}]", c))


def _digest_text(found: str) -> str:
    ordered = f"array_sort(transform({found}, x -> struct(x.s AS s, x.k AS k, x.e AS e)))"
    kinds = "array(" + ",".join(f"'{k}'" for k in KINDS) + ")"
    return f"array_join(transform({ordered}, x -> concat_ws(':', {kinds}[x.k], x.s, x.e)), ',')"


def scan(docs: DataFrame, text_col: str = "text", keep=None, window: int = WINDOW, classes=CLASSES, allow: str = ALLOW) -> DataFrame:
    """``docs`` with counts of each kind, base_sha256, spans (text) and found (array of k, s, e)."""
    keep = without(docs.columns if keep is None else keep, OUTPUTS)
    row = F.struct(*[column(c) for c in keep]) if keep else F.struct(F.lit(0).alias("none"))
    t = F.coalesce(column(text_col), F.lit(""))
    df = docs.select(row.alias("__row"), t.alias("__t"))
    empty = "cast(array() AS array<struct<s: int, e: int, m: string>>)"
    any_assign = "(contains(__t, '=') OR contains(__t, ':'))"
    quoted = "'" + ASSIGN.replace("\\", "\\\\").replace("'", "\\'") + "'"
    df = df.selectExpr(
        "__row", "__t",
        f"IF({any_assign}, {_matches('__t', ASSIGN)}, {empty}) AS __a",
        f"IF(contains(__t, 'AKIA'), {_matches('__t', f'AKIA[A-Z0-9]{{{ACCESS_LEAST - 4},}}')}, {empty}) AS __k",
        # runs are maximal, so asking for the least length finds the same runs as dropping short ones
        _matches("__t", f"[0-9a-f]{{{HEX_LEAST},}}") + " AS __h",
        *[_matches("__t", f"[{chars}]{{{window},}}") + f" AS __c{i}" for i, (_, chars, _) in enumerate(classes)],
    )
    tag = lambda src, k: f"transform({src}, x -> struct({k} AS k, x.s AS s, x.e AS e))"
    df = df.selectExpr(
        "__row",
        tag(f"filter(__a, x -> char_length(regexp_extract(x.m, {quoted}, 1)) >= {ASSIGN_LEAST})", 0) + " AS __a",
        tag("__k", 1) + " AS __k",
        tag("__h", 2) + " AS __h",
        *[f"__c{i}" for i in range(len(classes))],
    )
    df = df.selectExpr("__row", "__a", "__k", "__h", "concat(__a, __k, __h) AS __b", *[f"__c{i}" for i in range(len(classes))])
    quoted_allow = "'" + allow.replace("\\", "\\\\").replace("'", "\\'") + "'"
    parts = []
    for i, (_, chars, least) in enumerate(classes):
        free = "NOT exists(__b, b -> b.s < x.e AND x.s < b.e)"
        scored = f"""transform(filter(__c{i}, x -> {free} AND NOT regexp(x.m, {quoted_allow}) AND regexp(x.m, '[0-9]') AND regexp(x.m, '[A-Za-z]')),
            x -> struct(x.s AS s, {_entropy("x.m", _symbols(chars), window, least)} AS w))"""
        parts.append(f"transform(filter({scored}, y -> y.w IS NOT NULL), y -> struct(3 AS k, y.s + y.w.lo - 1 AS s, y.s + y.w.hi AS e))")
    # one span a region: later classes give way to those that overlap them
    df = df.selectExpr(
        "__row", "__a", "__k", "__h", "__b",
        f"""aggregate(array_sort(transform(concat({", ".join(parts)}), x -> struct(x.s AS s, x.e AS e))),
            cast(array() AS array<struct<k: int, s: int, e: int>>),
            (acc, x) -> IF(size(acc) > 0 AND acc[size(acc) - 1].e > x.s,
                concat(slice(acc, 1, size(acc) - 1), array(struct(3 AS k, acc[size(acc) - 1].s AS s, greatest(acc[size(acc) - 1].e, x.e) AS e))),
                concat(acc, array(struct(3 AS k, x.s AS s, x.e AS e))))) AS __e""",
    )
    df = df.selectExpr(
        "__row",
        "cast(size(__a) AS bigint) AS n_assign", "cast(size(__k) AS bigint) AS n_access",
        "cast(size(__h) AS bigint) AS n_hex", "cast(size(__e) AS bigint) AS n_entropy",
        f"sha2({_digest_text('__b')}, 256) AS base_sha256",
        f"{_digest_text('concat(__b, __e)')} AS spans",
        "concat(__b, __e) AS found",
    )
    return df.select(*[F.col("__row")[c].alias(c) for c in keep], *OUTPUTS)


def redact(text: Column, found: Column, mark: str = "[SECRET]") -> Column:
    """``text`` with the union of the found spans replaced by ``mark``."""
    merged = F.aggregate(
        F.array_sort(F.transform(found, lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e")))),
        F.array().cast("array<struct<s: int, e: int>>"),
        lambda acc, x: F.when(
            (F.size(acc) > 0) & (F.element_at(acc, F.size(acc))["e"] > x["s"]),
            F.concat(
                F.slice(acc, 1, F.size(acc) - 1),
                F.array(F.struct(F.element_at(acc, F.size(acc))["s"].alias("s"), F.greatest(F.element_at(acc, F.size(acc))["e"], x["e"]).alias("e"))),
            ),
        ).otherwise(F.concat(acc, F.array(x))),
    )
    whole = F.coalesce(text, F.lit(""))
    done = F.aggregate(
        merged,
        F.struct(F.lit(0).alias("at"), F.lit("").alias("out")),
        lambda acc, x: F.struct(
            x["e"].alias("at"),
            F.concat(acc["out"], F.substring(whole, acc["at"] + 1, x["s"] - acc["at"]), F.lit(mark)).alias("out"),
        ),
        lambda acc: F.concat(acc["out"], F.substring(whole, acc["at"] + 1, F.char_length(whole))),
    )
    return F.when(F.size(found) > 0, done).otherwise(text)
