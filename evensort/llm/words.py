"""Byte-level words of UTF-8 text and an Aho-Corasick automaton over word sequences."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable, Sequence

#: A-Z to a-z; a-z, 0-9 and every byte from 0x80 stay; all else becomes a space.
FOLD = bytes(
    c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256)
)


def words(text: bytes | None) -> list[bytes]:
    """Lower-cased (A-Z only) words of letters, digits and non-ASCII characters; null has none."""
    return text.translate(FOLD).split() if text else []


def word_offsets(text: bytes) -> list[tuple[int, int]]:
    """Byte span in ``text`` of each of its words, in order."""
    folded, spans, at = text.translate(FOLD), [], 0
    for w in folded.split():
        at = folded.index(w, at)
        spans.append((at, at + len(w)))
        at += len(w)
    return spans


class WordAutomaton:
    """Finds all places of many word sequences in one scan, overlaps included.

    Words are numbered; transitions live in one dictionary keyed by state and word, so
    memory is one entry for each distinct prefix of a pattern.
    """

    def __init__(self, patterns: Iterable[Sequence[bytes]]):
        self.patterns = list(dict.fromkeys(tuple(p) for p in patterns if p))
        self.vocab: dict[bytes, int] = {}
        for p in self.patterns:
            for w in p:
                self.vocab.setdefault(w, len(self.vocab))
        self.width = max(1, len(self.vocab))
        self.goto: dict[int, int] = {}
        ends: list[int] = [-1]
        children: list[list[tuple[int, int]]] = [[]]
        for n, p in enumerate(self.patterns):
            state = 0
            for w in p:
                k = self.vocab[w]
                step = self.goto.get(state * self.width + k)
                if step is None:
                    step = len(ends)
                    self.goto[state * self.width + k] = step
                    children[state].append((k, step))
                    ends.append(-1)
                    children.append([])
                state = step
            ends[state] = n
        self.fail = [0] * len(ends)
        self.found: list[tuple[int, ...]] = [()] * len(ends)
        queue = deque([0])
        while queue:
            state = queue.popleft()
            own = (ends[state],) if ends[state] >= 0 else ()
            self.found[state] = own + (self.found[self.fail[state]] if state else ())
            for k, step in children[state]:
                back = self.fail[state] if state else None
                while back is not None:
                    to = self.goto.get(back * self.width + k)
                    if to is not None:
                        self.fail[step] = to
                        break
                    back = self.fail[back] if back else None
                queue.append(step)

    def scan(self, text_words: Sequence[bytes]) -> list[tuple[int, tuple[int, ...]]]:
        """(index of the last word, pattern numbers that end there) in text order."""
        if self.vocab.keys().isdisjoint(text_words):
            return []
        goto, fail, found, width = self.goto.get, self.fail, self.found, self.width
        state, hits = 0, []
        for i, k in enumerate(map(self.vocab.get, text_words)):
            if k is None:
                state = 0
                continue
            step = goto(state * width + k)
            while step is None and state:
                state = fail[state]
                step = goto(state * width + k)
            state = step or 0
            if found[state]:
                hits.append((i, found[state]))
        return hits
