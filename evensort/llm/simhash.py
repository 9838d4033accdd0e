"""SimHash near-duplicates: fingerprints, a Gray-order hierarchical index, components.

Fingerprints: XXH64 (seed 42) of word shingles, repeats included; a bit is set if it is set
in more than half the hashes.

Links (at most ``threshold`` differing bits) are found exactly.  Distinct fingerprints are
cut into ``blocks`` bit blocks; two within the threshold agree on at least
``blocks - threshold`` of them, so each fingerprint goes to one bucket for every choice of
so many blocks.  In every bucket of two or more, fingerprints are sorted by Gray rank and
grouped into the nodes of a tree; a node keeps the bits its members share.  A node's
differing shared bits bound the distance of all its members from below, and go down the
tree as an accumulated sum, so whole groups are pruned.  Buckets give spanning links (a
tree of each bucket's components), never all pairs: no link between different texts is
lost to the components.  Buckets of over ``hot`` codes are first cut by further blocks.

Components come from alternating large-star and small-star steps on the spanning links,
with a checkpoint after each round.

Copies meet only in the count of distinct fingerprints (partial aggregates), so a group of
copies of any size costs one row a task.

Defined cases: no words (null or blank text): fingerprint zero, linked like any other; a
null id keeps its row, and takes part by its fingerprint: component_id is the smallest
non-null id reachable, or null; repeated rows come out as often as they went in; an empty
table gives an empty result.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ._arrow import append_columns, checkpoint, column, packed, unpacked

SHINGLE = 4
THRESHOLD = 4
#: One of five blocks: 5 buckets a fingerprint, of 12 or 13 bits.
BLOCKS = 5
FANOUT = 16
#: Buckets over so many codes are cut again: a tree then looks at a few thousand codes a query.
HOT = 4096
#: Rows gathered before finished buckets are searched; bounds a task's memory beside its largest bucket.
GATHER = 400_000

FIELDS = StructType([StructField("__fp", LongType())])


def fingerprint(hashes: np.ndarray) -> int:
    """64-bit majority of unsigned hashes; zero for none."""
    n = len(hashes)
    if n == 0:
        return 0
    ones = np.zeros(64, np.int64)
    for at in range(0, n, 65536):
        part = hashes[at : at + 65536].astype("<u8")
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = np.packbits(ones * 2 > n, bitorder="little")
    return int(bits.view("<u8")[0])


def shingle_hashes(text: bytes | None, size: int = SHINGLE) -> np.ndarray:
    from xxhash import xxh64_intdigest

    own = text.lower().split() if text else []  # A-Z only, and ASCII blanks only, on bytes
    if not own:
        return np.zeros(0, np.uint64)
    if len(own) <= size:
        return np.array([xxh64_intdigest(b" ".join(own), 42)], np.uint64)
    join = b" ".join
    made = [xxh64_intdigest(join(s), 42) for s in zip(*[own[i:] for i in range(size)])]
    return np.array(made, np.uint64)


def fingerprints(docs: DataFrame, text_col: str = "text", size: int = SHINGLE, keep=None) -> DataFrame:
    """``docs`` with ``__fp``, the fingerprint as a signed long."""

    def make():
        def kernel(texts):
            made = []
            for t in texts:
                f = fingerprint(shingle_hashes(t, size))
                made.append((f - (1 << 64) if f >> 63 else f,))
            return made

        return kernel

    return append_columns(docs, [text_col], make, FIELDS, keep)


def block_masks(blocks: int, threshold: int) -> list[int]:
    """Bit masks of all choices of ``blocks - threshold`` blocks."""
    if blocks <= threshold:
        raise ValueError("blocks must exceed the threshold")
    edges = [64 * i // blocks for i in range(blocks + 1)]
    single = [((1 << (e - s)) - 1) << s for s, e in zip(edges, edges[1:])]
    return [sum(c) for c in combinations(single, blocks - threshold)]


def gray_rank(codes: np.ndarray) -> np.ndarray:
    """Position of each code in the reflected Gray sequence."""
    rank = codes.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(shift)
    return rank


class GrayForest:
    """One Gray-order tree for every bucket of a run of buckets, all trees side by side.

    ``codes`` are sorted by bucket and, in a bucket, by Gray rank.  A node covers ``fanout``
    neighbours of the level below and keeps the bits that all of its codes share; ``added``
    has those that its parent doesn't share yet, so that a query's differences add up on the
    way down.  ``label`` is the component a code is known to be in, and a node's label is
    that of all its codes, or -1: a query skips nodes of its own component."""

    def __init__(self, codes: np.ndarray, sizes: np.ndarray, fanout: int):
        self.codes, self.label = codes, np.arange(len(codes))
        low, high, count = codes, codes, sizes.astype(np.int64)
        #: from the leaves up: each node's first child, number of children, pattern and mask
        self.levels: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        self.parents: list[np.ndarray] = []
        while True:
            nodes = -(-count // fanout)
            first = np.repeat(np.cumsum(count) - count, nodes) + _steps(nodes) * fanout
            children = np.minimum(first + fanout, np.repeat(np.cumsum(count), nodes)) - first
            low, high = np.bitwise_and.reduceat(low, first), np.bitwise_or.reduceat(high, first)
            self.levels.append((first, children, low, ~(low ^ high)))
            self.parents.append(np.repeat(np.arange(len(first)), children))
            count = nodes
            if (count <= 1).all():
                break
        masks = [level[3] for level in self.levels]
        self.added = [m & ~above[p] for m, above, p in zip(masks, masks[1:], self.parents[1:])] + masks[-1:]
        self._name_nodes()

    def _name_nodes(self) -> None:
        least = most = self.label
        self.named = []
        for first, *_ in self.levels:
            least, most = np.minimum.reduceat(least, first), np.maximum.reduceat(most, first)
            self.named.append(np.where(least == most, least, -1))

    def within(self, queries: np.ndarray, trees: np.ndarray, threshold: int, labels: np.ndarray | None = None, most: int = 1 << 62):
        """(query number, position) of the codes within ``threshold`` bits of each query in the
        tree of the given number, without those of the query's component ``labels``.  None if
        several queries would look at over ``most`` nodes of a level together."""
        who, at, sums = np.arange(len(queries)), trees, np.zeros(len(queries), np.int64)
        for (first, children, pattern, _), added, named in zip(self.levels[::-1], self.added[::-1], self.named[::-1]):
            sums = sums + np.bitwise_count((pattern[at] ^ queries[who]) & added[at])
            kept = sums <= threshold
            if labels is not None:
                kept &= named[at] != labels[who]
            who, at, sums = who[kept], at[kept], sums[kept]
            n = children[at]
            if n.sum() > most and len(queries) > 1:
                return None
            at, who, sums = np.repeat(first[at], n) + _steps(n), np.repeat(who, n), np.repeat(sums, n)
        # what the leaf's codes don't share is left to compare
        shared = self.levels[0][3][self.parents[0][at]]
        kept = sums + np.bitwise_count((self.codes[at] ^ queries[who]) & ~shared) <= threshold
        if labels is not None:
            kept &= self.label[at] != labels[who]
        return who[kept], at[kept]

    def join(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Put the codes of each pair into one component; the numbers of the pairs that did."""
        pairs, first = np.unique(np.stack([self.label[a], self.label[b]], 1), axis=0, return_index=True)
        root: dict[int, int] = {}
        used = []
        for (x, y), i in zip(pairs.tolist(), first.tolist()):
            while (up := root.setdefault(x, x)) != x:
                root[x] = x = root[up]
            while (up := root.setdefault(y, y)) != y:
                root[y] = y = root[up]
            if x != y:
                root[max(x, y)] = min(x, y)
                used.append(i)
        if used:
            to = np.arange(len(self.label))
            for x in sorted(root):
                to[x] = to[root[x]]
            self.label = to[self.label]
            self._name_nodes()
        return np.array(used, np.int64)


def _steps(counts: np.ndarray) -> np.ndarray:
    """0, 1, ... for each count, one after the other."""
    return np.arange(int(counts.sum())) - np.repeat(np.cumsum(counts) - counts, counts)


class GrayTree:
    """A forest of one tree, over codes in any order; positions are those in Gray order."""

    def __init__(self, codes: np.ndarray, fanout: int = FANOUT):
        self.order = np.argsort(gray_rank(codes), kind="stable")
        self.codes = codes[self.order]
        self.forest = GrayForest(self.codes, np.array([len(codes)]), fanout)

    def within(self, code: np.uint64, threshold: int, alive: np.ndarray) -> np.ndarray:
        """Positions of alive codes at most ``threshold`` bits from ``code``."""
        found = self.forest.within(np.array([code], np.uint64), np.zeros(1, np.int64), threshold)[1]
        return found[alive[found]]


#: Children of a node of the forest.
LEAF = FANOUT
#: Queries that go down the forest together, at first and at most, and the nodes they may meet on a level.
FIRST, TOGETHER, NODES = 1024, 20_000, 4_000_000


def forest_links(codes: np.ndarray, sizes: np.ndarray, threshold: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions (a, b) of spanning links of each bucket's components.

    Every code asks its bucket's tree once, in batches.  Links of a batch join components,
    later queries skip nodes of their own, so a dense group is found once and not as all
    pairs.  A batch that meets too many nodes is cut."""
    forest = GrayForest(codes, sizes, LEAF)
    tree = np.repeat(np.arange(len(sizes)), sizes)
    left, right = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    at, room = 0, FIRST
    while at < len(codes):
        end = min(len(codes), at + room)
        found = forest.within(codes[at:end], tree[at:end], threshold, forest.label[at:end], NODES)
        if found is None:
            room = max(1, room // 4)
            continue
        a, b = found[0] + at, found[1]
        if len(a):
            used = forest.join(a, b)
            left.append(a[used])
            right.append(b[used])
        at, room = end, min(TOGETHER, room * 2)
    return np.concatenate(left), np.concatenate(right)


def spanning_links(codes: np.ndarray, threshold: int) -> list[tuple[int, int]]:
    """Pairs (child, parent) of positions: a spanning tree of each component."""
    order = np.argsort(gray_rank(codes), kind="stable")
    a, b = forest_links(codes[order], np.array([len(codes)]), threshold)
    return list(zip(order[a].tolist(), order[b].tolist()))


def bucket_links(codes: np.ndarray, keys: np.ndarray, threshold: int) -> tuple[np.ndarray, np.ndarray]:
    """Links within runs of equal ``keys`` (sorted), each run in its own Gray-order tree."""
    starts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, np.int64)
    sizes = np.diff(np.r_[starts, len(keys)])
    # a bucket of one code has no pair
    paired = np.repeat(sizes > 1, sizes)
    codes, keys, sizes = codes[paired], keys[paired], sizes[sizes > 1]
    if not len(codes):
        return codes, codes
    codes = codes[np.lexsort((gray_rank(codes), keys))]
    a, b = forest_links(codes, sizes, threshold)
    return codes[a], codes[b]


def _exploded(codes: DataFrame, masks: list[int], *kept: str) -> DataFrame:
    """A row for each mask: its number ``t`` and the masked code ``key``, beside ``fp``."""
    masks = [m - (1 << 64) if m >> 63 else m for m in masks]
    tables = F.explode(F.array(*[F.struct(F.lit(i).alias("t"), F.lit(m).alias("m")) for i, m in enumerate(masks)]))
    return codes.select("fp", *kept, tables.alias("x")).select(
        *kept, F.col("x.t").alias("t"), F.col("fp").bitwiseAND(F.col("x.m")).alias("key"), "fp"
    )


def links(codes: DataFrame, threshold: int = THRESHOLD, blocks: int = BLOCKS, hot: int = HOT) -> DataFrame:
    """Spanning links (a, b) of distinct fingerprints in column ``fp``.

    A bucket of over ``hot`` codes is cut again: its codes agree on the bucket's blocks, so
    any two within the threshold agree on one of ``threshold + 1`` blocks of the other bits
    too.  There are at most as many such buckets as bucket keys (40,960 with 5 blocks)."""
    masks = block_masks(blocks, threshold)
    keyed = _exploded(codes, masks)
    large = checkpoint(keyed.groupBy("t", "key").count().where(F.col("count") > hot).select("t", "key"))
    none = F.lit(None).cast("int").alias("t2"), F.lit(None).cast("bigint").alias("key2")
    laid = keyed.select("t", "key", *none, "fp")
    if large.limit(1).count():
        marked = keyed.join(_bounded(large, blocks, threshold), ["t", "key"], "left_semi")
        cut = None
        for t, m in enumerate(masks):
            rest = _exploded(marked.where(F.col("t") == t).select("fp", F.col("t").alias("t1"), F.col("key").alias("key1")), _cut_rest(m, threshold + 1), "t1", "key1")
            rest = rest.select(F.col("t1").alias("t"), F.col("key1").alias("key"), F.col("t").alias("t2"), F.col("key").alias("key2"), "fp")
            cut = rest if cut is None else cut.unionByName(rest)
        laid = keyed.join(_bounded(large, blocks, threshold), ["t", "key"], "left_anti").select("t", "key", *none, "fp").unionByName(cut)
    bucket = ["t", "key", "t2", "key2"]
    laid = laid.repartition(*bucket).sortWithinPartitions(*bucket)
    laid = laid.select("t", "key", F.coalesce("t2", F.lit(-1)).alias("t2"), F.coalesce("key2", F.lit(0)).alias("key2"), "fp")

    def search(batches):
        held: list[tuple[np.ndarray, ...]] = []
        rows = 0

        def gathered():
            return [np.concatenate(x) for x in zip(*held)]

        def changes(columns):
            return np.flatnonzero(np.any([c[1:] != c[:-1] for c in columns[:4]], axis=0)) + 1

        def made(columns):
            fp = columns[4].view(np.uint64)
            run = np.zeros(len(fp), np.int64)
            run[changes(columns)] = 1
            a, b = bucket_links(fp, np.cumsum(run), threshold)
            for at in range(0, len(a), 100_000):
                part = [np.ascontiguousarray(x[at : at + 100_000]).view(np.int64) for x in (a, b)]
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in part], names=["a", "b"])

        for batch in batches:
            if batch.num_rows == 0:
                continue
            held.append(tuple(batch.column(i).to_numpy(zero_copy_only=False) for i in range(5)))
            rows += batch.num_rows
            if rows >= GATHER:
                columns = gathered()
                edges = changes(columns)
                cut = int(edges[-1]) if len(edges) else 0
                if cut:
                    yield from made([c[:cut] for c in columns])
                held = [tuple(c[cut:] for c in columns)]
                # a bucket that fills the buffer waits for as much again
                rows = 0
        if held:
            yield from made(gathered())

    schema = StructType([StructField("a", LongType()), StructField("b", LongType())])
    return laid.mapInArrow(search, schema)


def _bounded(large: DataFrame, blocks: int, threshold: int) -> DataFrame:
    """``large`` to be broadcast where the number of possible keys is small enough to."""
    widest = max(m.bit_count() for m in block_masks(blocks, threshold))
    return F.broadcast(large) if widest <= 16 else large


def _cut_rest(mask: int, pieces: int) -> list[int]:
    """Masks of ``pieces`` blocks of the bits outside ``mask``."""
    bits = [b for b in range(64) if not mask >> b & 1]
    edges = [len(bits) * i // pieces for i in range(pieces + 1)]
    return [sum(1 << b for b in bits[s:e]) for s, e in zip(edges, edges[1:])]


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root) for every node of an edge; root is the smallest node of its component.

    ``edges`` has long columns a and b.  Rounds repeat until none changes the edges."""
    edges = edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    edges = checkpoint(edges.distinct())
    before = None
    for _ in range(rounds):
        state = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").bitwiseAND(F.lit((1 << 40) - 1)))).first()
        if tuple(state) == before:
            break
        before = tuple(state)
        both = edges.union(edges.select("b", "a")).toDF("u", "v")
        low = checkpoint(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")))
        # large star: neighbours above a node move to the smallest of its neighbourhood
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("a"), F.col("m").alias("b"))
        large = checkpoint(large.where("a <> b").distinct())
        # small star: neighbours below a node, and the node, move to the smallest of them
        low = checkpoint(large.groupBy("a").agg(F.min("b").alias("m")))
        small = large.join(low, "a").select("b", "m", "a")
        small = small.select(F.col("b").alias("a"), F.col("m").alias("b")).union(low.select("a", F.col("m").alias("b")))
        edges = checkpoint(small.where("a <> b").distinct())
    else:
        raise RuntimeError("components did not settle")
    return edges.groupBy("a").agg(F.min("b").alias("root")).select(F.col("a").alias("node"), "root")


def classes(marked: DataFrame, id_col: str = "doc_id", threshold: int = THRESHOLD, blocks: int = BLOCKS) -> DataFrame:
    """(fp, component_id) for each distinct ``__fp`` of rows with ids."""
    known = checkpoint(marked.groupBy(F.col("__fp").alias("fp")).agg(F.min(column(id_col)).alias("least")))
    root = components(links(known.select("fp"), threshold, blocks))
    joined = known.join(root, F.col("fp") == F.col("node"), "left")
    joined = checkpoint(joined.select("fp", "least", F.coalesce("root", "fp").alias("root")))
    least = checkpoint(joined.groupBy("root").agg(F.min("least").alias("component_id")))
    return joined.join(least, "root").select("fp", "component_id")


def near_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: int = THRESHOLD, blocks: int = BLOCKS, size: int = SHINGLE
) -> DataFrame:
    """(id, __fp, component_id) for every row of ``docs``."""
    own = docs.select(column(id_col).alias("__id"), column(text_col).alias("__text"))
    marked = checkpoint(fingerprints(own, "__text", size, keep=["__id"]))
    found = checkpoint(classes(marked, "__id", threshold, blocks))
    joined = marked.join(found, F.col("__fp") == F.col("fp"))
    return joined.select(F.col("__id").alias(id_col), "__fp", "component_id")


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE, **how) -> DataFrame:
    """``docs`` with one row of each component: that with the smallest id.

    Rows are told apart by id and fingerprint; of rows equal in both one stays.  Null ids come last."""
    whole = packed(docs, __id=column(id_col), __text=column(text_col))
    marked = checkpoint(fingerprints(whole, "__text", size, keep=["__id"]))
    found = checkpoint(classes(marked, "__id", **how))
    own = marked.join(found, F.col("__fp") == F.col("fp")).select("__id", "fp", "component_id")
    first = F.min(F.struct(F.col("__id").isNull(), F.col("__id"), F.col("fp"))).alias("x")
    # an unset component_id (all ids null) is told apart by fingerprint
    alone = F.when(F.col("component_id").isNull(), F.col("fp"))
    stay = own.groupBy("component_id", alone.alias("alone")).agg(first)
    stay = checkpoint(stay.select(F.col("x.__id").alias("stay_id"), F.col("x.fp").alias("stay_fp")))
    repeated = marked.groupBy("__id").count().where("count > 1").limit(1).count()
    same = F.col("__id").eqNullSafe(F.col("stay_id"))
    if not repeated:
        return unpacked(whole.join(stay, same, "left_semi"), docs.columns)
    rows = fingerprints(whole, "__text", size)
    kept = rows.join(stay, same & (F.col("__fp") == F.col("stay_fp")), "left_semi").dropDuplicates(["__id", "__fp"])
    return unpacked(kept, docs.columns)
