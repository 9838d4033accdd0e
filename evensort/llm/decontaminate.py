"""Benchmark decontamination with one Aho-Corasick automaton over normalised items.

Items (questions, answers or both: any number of text columns) are folded to words, cut
into windows of consecutive words, and put into one word automaton; every document is
scanned once.  Hits are word positions; :func:`hit_spans` maps them to byte offsets of the
original text.

An automaton is broadcast, so its size is bounded (``max_automaton_words``).  A larger
benchmark is cut into groups of items within the bound, the documents are scanned once a
group, and hit runs and item ids of a row are merged, so every benchmark gives the same
rows as one automaton would.  An item over the bound on its own is cut where its windows
allow.  :func:`find_by_join` gives only the distinct (id, item_id) pairs, by an equi-join.

Defined cases: null or wordless text has no words and no hits; wordless items never occur;
items of fewer words than a window are one window; repeated items count by their own ids,
an id with several rows counts once; null ids are skipped in ``items``; an empty benchmark
leaves every document clean; other columns pass through.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BooleanType, LongType, StringType, StructField, StructType

from ._arrow import append_columns, checkpoint, column, without
from .words import WordAutomaton, word_offsets, words

WINDOW = 10
#: Bound of the broadcast side: words of all windows together.
MAX_AUTOMATON_WORDS = 20_000_000

FIELDS = StructType(
    [
        StructField("n_words", LongType()),
        StructField("n_hit", LongType()),
        StructField("n_items", LongType()),
        StructField("items_sha256", StringType()),
        StructField("contaminated", BooleanType()),
        StructField("items", ArrayType(StringType())),
        StructField("hits", ArrayType(ArrayType(LongType()))),
    ]
)
#: The column added to rows numbered for a scan in groups.
FIELDS_WORDS = StructType([StructField("words", LongType())])


def windows(item_words: list[bytes], size: int) -> list[tuple[bytes, ...]]:
    """Runs of ``size`` consecutive words; a shorter item is one window, an empty one none."""
    if not item_words:
        return []
    return [tuple(item_words[i : i + size]) for i in range(max(1, len(item_words) - size + 1))]


def digest(ids) -> str:
    return hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest()


class Scanner:
    """Automaton plus, for each window, the items it stands in."""

    def __init__(self, items: list[tuple[str, bytes | None]], size: int = WINDOW):
        owners: dict[tuple[bytes, ...], set[str]] = {}
        for item_id, text in items:
            for window in windows(words(text), size):
                owners.setdefault(window, set()).add(item_id)
        self.automaton = WordAutomaton(owners)
        self.owners = [owners[p] for p in self.automaton.patterns]

    def __call__(self, text: bytes | None) -> tuple:
        own = words(text)
        ids: set[str] = set()
        runs: list[list[int]] = []
        for end, found in self.automaton.scan(own):
            for n in found:
                ids |= self.owners[n]
            start = end + 1 - max(len(self.automaton.patterns[n]) for n in found)
            while runs and start <= runs[-1][1]:
                start = min(start, runs.pop()[0])
            runs.append([start, end + 1])
        named = sorted(i for i in ids if i is not None)
        hit = sum(e - s for s, e in runs)
        return len(own), hit, len(named), digest(named), hit > 0, named, runs


def scan(
    docs: DataFrame,
    benchmark: DataFrame,
    text_col: str = "text",
    item_id_col: str = "item_id",
    item_text_cols: tuple[str, ...] = ("text",),
    window: int = WINDOW,
    keep=None,
    max_automaton_words: int = MAX_AUTOMATON_WORDS,
) -> DataFrame:
    """``docs`` with n_words, n_hit, n_items, items_sha256, contaminated, items and hits."""
    sizes = [F.coalesce(F.octet_length(column(c)), F.lit(0)) for c in item_text_cols]
    total = benchmark.agg(F.sum(sum(sizes, F.lit(0)))).first()[0] or 0
    # a word and its separator take two bytes at least, and each starts one window
    bound = int(max_automaton_words * 2 / window)
    rows = benchmark.select(column(item_id_col).cast("string"), *[column(c) for c in item_text_cols])
    texts = ((r[0], t.encode()) for r in (rows.collect() if total <= bound else rows.toLocalIterator()) for t in r[1:] if t)
    if total <= bound:
        shared = docs.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, list(texts), window))
        return append_columns(docs, [text_col], lambda: _kernel(shared), FIELDS, keep)
    if bound < 2 * window:
        raise ValueError(f"an automaton of {max_automaton_words} words has no room for a window")
    return _scan_in_groups(docs, groups(texts, bound, window), text_col, window, keep)


def _scan_in_groups(docs, grouped, text_col, window, keep):
    """One job a group over rows numbered once; then the rows with hits are merged by number."""
    keep = without(docs.columns if keep is None else keep, FIELDS.names)
    row = F.struct(*[column(c) for c in keep]) if keep else F.struct(F.lit(0).alias("none"))
    whole = docs.select(F.monotonically_increasing_id().alias("n"), row.alias("kept"), column(text_col).alias("t"))
    whole = checkpoint(append_columns(whole, ["t"], lambda: lambda texts: [(len(words(t)),) for t in texts], FIELDS_WORDS))
    found = None
    for items in grouped:
        shared = docs.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, items, window))
        hit = append_columns(whole.select("n", "t"), ["t"], lambda shared=shared: _kernel(shared), FIELDS, ["n"])
        hit = checkpoint(hit.where("contaminated").select("n", F.struct("items", "hits").alias("x")))
        shared.unpersist()
        found = hit if found is None else found.union(hit)
    found = found.groupBy("n").agg(F.collect_list("x").alias("found"))
    joined = whole.select("n", "kept", "words").join(found, "n", "left")
    out = append_columns(joined, ["words", "found"], lambda: lambda n, found: [_merged(*x) for x in zip(n, found)], FIELDS, ["kept"])
    return out.select(*[F.col("kept")[c].alias(c) for c in keep], *FIELDS.names)


def _merged(n_words: int, found: list[dict] | None) -> tuple:
    """The row of :class:`Scanner` from the items and hits of several."""
    named = sorted({i for x in found or () for i in x["items"]})
    runs: list[list[int]] = []
    for s, e in sorted(r for x in found or () for r in x["hits"]):
        if runs and s <= runs[-1][1]:
            runs[-1][1] = max(runs[-1][1], e)
        else:
            runs.append([s, e])
    hit = sum(e - s for s, e in runs)
    return n_words, hit, len(named), digest(named), hit > 0, named, runs


def groups(items: Iterable[tuple[str, bytes]], bound: int, window: int) -> Iterator[list[tuple[str, bytes]]]:
    """Lists of items of at most ``bound`` bytes each (one piece at least); one empty list for none.

    An item over the bound is cut into runs of words that overlap by ``window - 1``, so no window is lost."""
    held: list[tuple[str, bytes]] = []
    size, made = 0, False
    for item_id, text in items:
        for piece in _pieces(text, bound, window):
            if held and size + len(piece) > bound:
                yield held
                held, size, made = [], 0, True
            held.append((item_id, piece))
            size += len(piece)
    if held or not made:
        yield held


def _pieces(text: bytes, bound: int, window: int) -> Iterator[bytes]:
    if len(text) <= bound:
        yield text
        return
    own, at = words(text), 0
    while own:
        end, size = at, 0
        while end < len(own) and (end < at + window or size + len(own[end]) < bound):
            size += len(own[end]) + 1
            end += 1
        yield b" ".join(own[at:end])
        if end == len(own):
            return
        at = end - window + 1


_BUILT: dict[str, Scanner] = {}


def _kernel(shared):
    # a reused worker keeps the automaton of the last benchmark
    key, items, window = shared.value
    if key not in _BUILT:
        _BUILT.clear()
        _BUILT[key] = Scanner(items, window)
    scanner = _BUILT[key]
    return lambda texts: [scanner(t) for t in texts]


def hit_spans(text: bytes, hits: list[list[int]]) -> list[tuple[int, int]]:
    """Byte spans in the original text of word runs [start, end)."""
    at = word_offsets(text)
    return [(at[s][0], at[e - 1][1]) for s, e in hits]


def find_by_join(
    docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id",
    item_text_col: str = "text", window: int = WINDOW,
) -> DataFrame:
    """Distinct (id, item_id) pairs by an equi-join of window texts; no positions or counts.

    Native: folded words, joined on the window's length and text, so no pair is lost or
    invented.  Items shorter than a window need windows of their own length.
    """
    fold = lambda c: F.filter(
        F.split(F.translate(column(c), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"),
        lambda w: w != "",
    )
    item = benchmark.select(column(item_id_col).cast("string").alias("item_id"), fold(item_text_col).alias("w"))
    item = item.where("size(w) > 0").withColumn("n", F.least(F.size("w"), F.lit(window)))
    lengths = [r[0] for r in item.select("n").distinct().collect()]
    cut = "explode(transform(sequence(1, size(w) - n + 1), i -> concat_ws(' ', slice(w, i, n))))"
    item = item.selectExpr("item_id", "n", f"{cut} AS gram").distinct()
    doc = docs.select(column(id_col).alias("id"), fold(text_col).alias("w"))
    found = None
    for n in lengths:
        own = doc.withColumn("n", F.lit(n)).where("size(w) >= n").selectExpr("id", "n", f"{cut} AS gram")
        found = own if found is None else found.unionByName(own)
    if found is None:
        return item.select(F.lit(None).cast(docs.schema[id_col].dataType).alias("id"), "item_id").limit(0)
    return found.join(item, ["n", "gram"]).select("id", "item_id").distinct()
