"""Sorters of one block and mergers of sorted runs, with counts of the work they do.

Each sorter takes a vector of keys and gives a stable permutation.  The quicksorts partition
a range of keys and places in memory, where equal keys lose their order; a last pass puts
each run of equal keys back in order of place, and does not touch unequal ones.

``Stats`` counts what the partitionings, insertions and heaps do: comparisons, exchanged
or moved elements, branches that hang on a comparison's result, recursion depth, bad
partitions and heapsort fallbacks.  Steps over whole arrays do the comparisons of the
element-wise scan and count them; small ranges and heaps are counted one by one.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

SMALL = 16
#: Elements that block partitioning looks at before it exchanges.
BLOCK = 128
#: A partition is bad if its smaller side has under one of so many elements.
BAD = 8


@dataclass
class Stats:
    comparisons: int = 0
    moves: int = 0
    branches: int = 0
    depth: int = 0
    bad_partitions: int = 0
    fallbacks: int = 0


def _insert_all(values: np.ndarray, places: np.ndarray, ranges: list[tuple[int, int]], s: Stats) -> None:
    """Insertion sort of many small ranges at once, by the number of smaller elements.

    An element meets those over it in front, and one more that stops it if there is one."""
    for at in range(0, len(ranges), 4096):
        part = np.array(ranges[at : at + 4096], np.int64)
        start, n = part[:, 0], part[:, 1] - part[:, 0]
        width = int(n.max(initial=0))
        if width < 2:
            continue
        column = np.arange(width)
        held = column < n[:, None]
        spot = np.where(held, start[:, None] + column, 0)
        v = values[spot]
        both = held[:, :, None] & held[:, None, :] & (column[:, None] < column)[None]
        over = ((v[:, :, None] > v[:, None, :]) & both).sum(1)
        shifts = int(over.sum())
        s.comparisons += shifts + int(((over < column) & held).sum())
        s.branches += shifts + int(((over < column) & held).sum())
        s.moves += shifts
        under = ((v[:, :, None] > v[:, None, :]) & held[:, None, :] & held[:, :, None]).sum(2)
        rank = under + ((v[:, :, None] == v[:, None, :]) & both).sum(1)
        to = (start[:, None] + rank)[held]
        moved_values, moved_places = v[held], places[spot][held]
        values[to], places[to] = moved_values, moved_places


def _heapsort(values: np.ndarray, places: np.ndarray, lo: int, hi: int, s: Stats) -> None:
    """Heapsort of a range: a heap of the largest, whose root goes to the end each time."""
    work = list(zip(values[lo:hi].tolist(), places[lo:hi].tolist()))
    n, compared, moved = len(work), 0, 0

    def sink(i: int, end: int) -> None:
        nonlocal compared, moved
        item = work[i]
        while (child := 2 * i + 1) < end:
            if child + 1 < end:
                compared += 1
                child += work[child][0] < work[child + 1][0]
            compared += 1
            if work[child][0] <= item[0]:
                break
            work[i] = work[child]
            moved += 1
            i = child
        work[i] = item

    for i in range(n // 2 - 1, -1, -1):
        sink(i, n)
    for end in range(n - 1, 0, -1):
        work[0], work[end] = work[end], work[0]
        moved += 2
        sink(0, end)
    s.comparisons += compared
    s.branches += compared
    s.moves += moved
    values[lo:hi] = [v for v, _ in work]
    places[lo:hi] = [p for _, p in work]


def _swap(values, places, a, b) -> None:
    values[a], values[b] = values[b], values[a]
    places[a], places[b] = places[b], places[a]


def _middle(v: np.ndarray, s: Stats) -> int:
    """Place of the median of the ends and the middle."""
    s.comparisons += 3
    s.branches += 3
    return sorted(((v[0], 0), (v[len(v) // 2], len(v) // 2), (v[-1], len(v) - 1)), key=lambda x: x[0])[1][1]


def _root_sample(v: np.ndarray, s: Stats) -> int:
    """Place of the median of about sqrt(n) evenly spaced values."""
    m = max(3, math.isqrt(len(v)) | 1)
    at = np.linspace(0, len(v) - 1, m).astype(np.int64)
    # quickselect takes about three comparisons an element
    s.comparisons += 3 * m
    return int(at[np.argpartition(v[at], m // 2)[m // 2]])


def _scan_from_both_ends(v: np.ndarray, p: np.ndarray, pivot, s: Stats) -> int:
    """Two-ended partitioning: what is not under the pivot on the left changes places with
    what is not over it on the right, until the scans meet.  The number of elements left."""
    left, right = np.flatnonzero(v >= pivot), np.flatnonzero(v <= pivot)[::-1]
    m = min(len(left), len(right))
    pairs = int(np.count_nonzero(left[:m] < right[:m]))
    a, b = left[:pairs], right[:pairs]
    _swap_all(v, p, a, b)
    s.comparisons += len(v) + 2
    s.moves += 2 * pairs
    # the left scan stops at its next element, or at one that came over last
    stop = int(left[pairs]) if pairs < len(left) else len(v)
    return min(stop, int(right[pairs - 1])) if pairs else stop


def _swap_all(v, p, a, b) -> None:
    v[a], v[b] = v[b], v[a]
    p[a], p[b] = p[b], p[a]


def _by_blocks(v: np.ndarray, p: np.ndarray, pivot, s: Stats) -> int:
    """Block partitioning: comparisons only store positions in two buffers, one for a block
    from each end; elements are exchanged when both blocks have been read."""
    lo, hi = 0, len(v)
    left = right = np.zeros(0, np.int64)
    while hi - lo > 2 * BLOCK:
        if not len(left):
            left = lo + np.flatnonzero(v[lo : lo + BLOCK] >= pivot)
            s.comparisons += BLOCK
        if not len(right):
            right = hi - 1 - np.flatnonzero(v[hi - BLOCK : hi][::-1] <= pivot)
            s.comparisons += BLOCK
        m = min(len(left), len(right))
        _swap_all(v, p, left[:m], right[:m])
        s.moves += 2 * m
        left, right = left[m:], right[m:]
        # which block is used up
        s.branches += 2
        lo += BLOCK * (not len(left))
        hi -= BLOCK * (not len(right))
    # what is left in the middle, a part-read block included
    return lo + _scan_from_both_ends(v[lo:hi], p[lo:hi], pivot, s)


def _quick(keys: np.ndarray, s: Stats, pick: Callable, partition: Callable, depth_limit: int | None, skip_equal: bool) -> np.ndarray:
    """Two-way quicksort.  ``skip_equal``: a pivot equal to the one that bounds a range from
    below means that its copies stand first; they are split off and done."""
    places = np.arange(len(keys))
    values = keys.copy()
    small: list[tuple[int, int]] = []
    work = [(0, len(keys), 1, None)]
    scanned = partition is _scan_from_both_ends
    while work:
        lo, hi, depth, floor = work.pop()
        n = hi - lo
        s.depth = max(s.depth, depth)
        if n <= SMALL:
            small.append((lo, hi))
            continue
        if depth_limit is not None and depth > depth_limit:
            s.fallbacks += 1
            _heapsort(values, places, lo, hi, s)
            continue
        v, p = values[lo:hi], places[lo:hi]
        pivot = v[pick(v, s)]
        if skip_equal and floor is not None:
            s.comparisons += 1
            s.branches += 1
            if pivot == floor:
                over = v > pivot
                order = np.argsort(over, kind="stable")
                s.comparisons += n
                s.moves += n
                v[:], p[:] = v[order], p[order]
                work.append((lo + n - int(over.sum()), hi, depth + 1, None))
                continue
        before = s.comparisons
        cut = partition(v, p, pivot, s)
        if scanned:
            s.branches += s.comparisons - before
        # the pivot alone is the smallest: it has its place
        cut = min(max(cut, 1), n - 1)
        if min(cut, n - cut) < n / BAD:
            s.bad_partitions += 1
        work.append((lo, lo + cut, depth + 1, floor))
        work.append((lo + cut, hi, depth + 1, pivot))
    _insert_all(values, places, small, s)
    return places


def plain_quick(keys: np.ndarray, s: Stats) -> np.ndarray:
    return _quick(keys, s, _middle, _scan_from_both_ends, None, False)


def intro(keys: np.ndarray, s: Stats) -> np.ndarray:
    return _quick(keys, s, _middle, _scan_from_both_ends, 2 * int(math.log2(max(2, len(keys)))), False)


def branchless(keys: np.ndarray, s: Stats) -> np.ndarray:
    return _quick(keys, s, _root_sample, _by_blocks, 2 * int(math.log2(max(2, len(keys)))), True)


def three_way(keys: np.ndarray, s: Stats) -> np.ndarray:
    """Pattern-defeating quicksort in three parts.  A range may have floor(log2 N) bad
    partitions on its path from the whole; the one that reaches it goes to heapsort.  After a
    bad one some elements change places, and a range found in order is done."""
    places, values = np.arange(len(keys)), keys.copy()
    small: list[tuple[int, int]] = []
    work = [(0, len(keys), 1, max(1, int(math.log2(max(2, len(keys))))))]
    while work:
        lo, hi, depth, budget = work.pop()
        n = hi - lo
        s.depth = max(s.depth, depth)
        if n <= SMALL:
            small.append((lo, hi))
            continue
        if budget <= 0:
            s.fallbacks += 1
            _heapsort(values, places, lo, hi, s)
            continue
        v, p = values[lo:hi], places[lo:hi]
        pivot = v[_middle(v, s)]
        under, same = v < pivot, v == pivot
        a, b = int(under.sum()), int(same.sum())
        s.comparisons += n + n - a
        s.branches += n + n - a
        wanted = np.where(under, 0, np.where(same, 1, 2))
        homes = np.repeat([0, 1, 2], [a, b, n - a - b])
        moved = int((wanted != homes).sum())
        s.moves += moved
        if moved:
            order = np.argsort(wanted, kind="stable")
            v[:], p[:] = v[order], p[order]
        else:
            # in parts already: perhaps in order
            drops = np.flatnonzero(v[1:] < v[:-1])
            looked = int(drops[0]) + 1 if len(drops) else n - 1
            s.comparisons += looked
            s.branches += looked
            if not len(drops):
                continue
        bad = min(a, n - a - b) < n / BAD and b < n / 2
        if bad:
            s.bad_partitions += 1
            for side, m in ((lo, a), (lo + a + b, n - a - b)):
                if m > SMALL:
                    for x, y in ((0, m // 4), (m - 1, m - m // 4)):
                        _swap(values, places, side + x, side + y)
                    s.moves += 4
        work.append((lo, lo + a, depth + 1, budget - bad))
        work.append((lo + a + b, hi, depth + 1, budget - bad))
    _insert_all(values, places, small, s)
    return places


def heap(keys: np.ndarray, s: Stats) -> np.ndarray:
    places, values = np.arange(len(keys)), keys.copy()
    _heapsort(values, places, 0, len(keys), s)
    return places


def merge_block(keys: np.ndarray, s: Stats) -> np.ndarray:
    """Bottom-up mergesort: neighbouring runs of doubling width."""
    places, values = np.arange(len(keys)), keys.copy()
    ranges = [(i, min(i + SMALL, len(keys))) for i in range(0, len(keys), SMALL)]
    _insert_all(values, places, ranges, s)
    runs = [places[a:b] for a, b in ranges]
    while len(runs) > 1:
        s.depth += 1
        pairs = [runs[i : i + 2] for i in range(0, len(runs), 2)]
        runs = [_merge_two(keys, *p, s) if len(p) == 2 else p[0] for p in pairs]
    return runs[0] if runs else np.zeros(0, np.int64)


def radix(keys: np.ndarray, s: Stats) -> np.ndarray:
    """Least significant digit first, 16 bits a pass, on the order-preserving unsigned image."""
    image = keys.astype(np.int64).view(np.uint64) ^ np.uint64(1 << 63)
    order = np.arange(len(keys))
    for shift in (0, 16, 32, 48):
        digit = (image[order] >> np.uint64(shift)) & np.uint64(0xFFFF)
        if len(digit) and (digit == digit[0]).all():
            continue
        order = order[np.argsort(digit.astype(np.uint16), kind="stable")]
        s.moves += len(order)
    return order


def _merge_two(keys, a: np.ndarray, b: np.ndarray, s: Stats) -> np.ndarray:
    """Stable merge of two runs by ranks: ``a`` goes first among equal keys.

    Each output takes a comparison until one run is used up."""
    if len(a) and len(b):
        x, y = keys[a[-1]], keys[b[-1]]
        compared = len(a) + int(np.searchsorted(keys[b], x, side="left")) if x <= y else len(b) + int(np.searchsorted(keys[a], y, side="right"))
        s.comparisons += compared
        s.branches += compared
    s.moves += len(a) + len(b)
    at = np.searchsorted(keys[a], keys[b], side="right") + np.arange(len(b))
    out = np.empty(len(a) + len(b), np.int64)
    free = np.ones(len(out), bool)
    free[at] = False
    out[at], out[free] = b, a
    return out


SORTERS: dict[str, Callable[[np.ndarray, Stats], np.ndarray]] = {
    "plain_quick": plain_quick,
    "intro": intro,
    "branchless": branchless,
    "three_way": three_way,
    "heap": heap,
    "merge_block": merge_block,
    "radix": radix,
}


def permutation(kernel: str, keys: np.ndarray, stats: Stats | None = None) -> np.ndarray:
    """The stable sorting permutation by a named kernel."""
    if kernel not in SORTERS:
        raise ValueError(f"unknown kernel {kernel}")
    return _restored(keys, SORTERS[kernel](keys, stats or Stats()))


def _restored(keys: np.ndarray, order: np.ndarray) -> np.ndarray:
    """``order`` with each run of equal keys in order of place; unequal neighbours stay."""
    own = keys[order]
    run = np.cumsum(np.r_[0, own[1:] != own[:-1]]) if len(own) else own
    return order[np.lexsort((order, run))]


def classify(keys: np.ndarray, splitters: np.ndarray) -> np.ndarray:
    """Bucket of each key among sorted splitters (equal keys left), by an implicit search
    tree: each level is one comparison of the whole vector, without branches."""
    depth = max(1, math.ceil(math.log2(len(splitters) + 1)))
    # fill to a full tree with the largest splitter; the surplus is clipped
    full = np.concatenate([splitters, np.repeat(splitters[-1:], (1 << depth) - 1 - len(splitters))]) if len(splitters) else splitters
    if not len(full):
        return np.zeros(len(keys), np.int64)
    low = np.zeros(len(keys), np.int64)
    for level in range(depth - 1, -1, -1):
        low += (keys > full[low + (1 << level) - 1]).astype(np.int64) << level
    return np.minimum(low, len(splitters))


# ---- mergers: sorted runs of places into one order ----


def merge_tournament(keys: np.ndarray, runs: list[np.ndarray], s: Stats | None = None) -> np.ndarray:
    """A loser tree over the runs' heads: each output replays one path from leaf to root."""
    s = s or Stats()
    runs = [r for r in runs if len(r)]
    if not runs:
        return np.zeros(0, np.int64)
    k = 1 << max(0, len(runs) - 1).bit_length()
    values = [keys[r].tolist() for r in runs] + [[]] * (k - len(runs))
    heads = [0] * k
    done = (1, 0, 0)

    def head(i: int):
        return (0, values[i][heads[i]], i) if heads[i] < len(values[i]) else done

    tree, winners = [0] * k, list(range(k))
    level = winners
    width = k
    while width > 1:
        following = []
        for j in range(0, width, 2):
            a, b = level[j], level[j + 1]
            s.comparisons += 1
            lose, win = (b, a) if head(a) <= head(b) else (a, b)
            tree[(width + j) // 2] = lose
            following.append(win)
        level, width = following, width // 2
    winner, out = level[0], []
    for _ in range(sum(map(len, runs))):
        out.append(runs[winner][heads[winner]])
        heads[winner] += 1
        node = (winner + k) // 2
        while node >= 1:
            s.comparisons += 1
            if head(tree[node]) < head(winner):
                tree[node], winner = winner, tree[node]
            node //= 2
    s.moves += len(out)
    return np.array(out, np.int64)


def merge_pairs(keys: np.ndarray, runs: list[np.ndarray], s: Stats | None = None) -> np.ndarray:
    """The tournament's fast form: balanced merges of neighbouring runs by whole vectors."""
    s = s or Stats()
    runs = [r for r in runs if len(r)]
    while len(runs) > 1:
        pairs = [runs[i : i + 2] for i in range(0, len(runs), 2)]
        runs = [_merge_two(keys, *p, s) if len(p) == 2 else p[0] for p in pairs]
    return runs[0] if runs else np.zeros(0, np.int64)


def merge_heap(keys: np.ndarray, runs: list[np.ndarray], s: Stats | None = None) -> np.ndarray:
    """A binary heap of the runs' heads: the root is replaced by its run's next element, which
    sinks with two comparisons a level."""
    s = s or Stats()
    streams = [keys[r].tolist() for r in runs if len(r)]
    places = [r.tolist() for r in runs if len(r)]
    # of equal keys the earlier run's goes first
    heap_ = sorted((v[0], i, 0) for i, v in enumerate(streams))
    s.comparisons += max(0, int(len(heap_) * math.log2(max(1, len(heap_)))))
    out, n, compared = [], len(heap_), 0
    while n:
        _, i, at = heap_[0]
        out.append(places[i][at])
        if at + 1 < len(streams[i]):
            item = (streams[i][at + 1], i, at + 1)
        else:
            n -= 1
            item = heap_[n]
        k = 0
        while (child := 2 * k + 1) < n:
            if child + 1 < n:
                compared += 1
                child += heap_[child + 1] < heap_[child]
            compared += 1
            if item <= heap_[child]:
                break
            heap_[k] = heap_[child]
            k = child
        heap_[k] = item
    s.comparisons += compared
    s.branches += compared
    s.moves += len(out)
    return np.array(out, np.int64)


def merge_resort(keys: np.ndarray, runs: list[np.ndarray], s: Stats | None = None) -> np.ndarray:
    """Runs appended in order and sorted again: by the library's sort, or, where the work is
    asked for, by the block sorter that a program would use."""
    every = np.concatenate(runs) if runs else np.zeros(0, np.int64)
    if s is None:
        return every[np.argsort(keys[every], kind="stable")]
    s.moves += len(every)
    return every[permutation("intro", keys[every], s)]


def merge_auto(keys: np.ndarray, runs: list[np.ndarray], s: Stats | None = None) -> np.ndarray:
    """Vector merges up to four runs, the tree above."""
    return (merge_pairs if len([r for r in runs if len(r)]) <= 4 else merge_tournament)(keys, runs, s)


MERGERS = {
    "tournament": merge_tournament,
    "pairs": merge_pairs,
    "binary_heap": merge_heap,
    "resort": merge_resort,
    "auto": merge_auto,
}
