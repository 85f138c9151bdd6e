"""Counts of greedy word pieces by one linear pass over an automaton.

The trie of the vocabulary has word-start pieces under the root and pieces that
go on a word under a second root.  Every node has a failure link to the node for
what is left after greedy matching took pieces from its string, and the number
of pieces so taken (popped); both are computed once, in breadth-first order.
Counting follows the word's bytes, adding popped counts as it fails over; no
piece is built, and a byte is read once.

Defined cases.  A null or empty text has no words and no pieces.  A word that
the vocabulary cannot spell counts as one unknown piece.  Extra columns pass
through whatever their names, those named like the results are replaced;
repeated rows are counted alike, each by itself.
"""

from __future__ import annotations

import base64
from collections import deque
from functools import cache
from itertools import chain

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import Recent, few_collections, struct_of, text_bytes, with_results

#: Words that the cache keeps at most, twice over, and bytes from which on it keeps none.
CACHED_WORDS, LONG_WORD = 150_000, 64


class Pieces:
    """``start``: pieces that begin a word; ``inner``: pieces that go on one; both of bytes."""

    def __init__(self, start: list[bytes], inner: list[bytes]):
        self.next: list[dict[int, int]] = [{}, {}]
        ends = {self._add(0, p) for p in start if p} | {self._add(1, p) for p in inner if p}
        n = len(self.next)
        # fail -1: the string can't be split into pieces and a rest inside the trie
        self.fail, self.popped = [-1] * n, [0] * n
        queue = deque()
        for root in (0, 1):
            queue += [(root, byte, child) for byte, child in self.next[root].items()]
        while queue:
            node, byte, child = queue.popleft()
            if child in ends:
                self.fail[child], self.popped[child] = 1, 1
            else:
                at, taken = self.fail[node], self.popped[node]
                while at >= 0 and byte not in self.next[at]:
                    taken += self.popped[at]
                    at = self.fail[at]
                if at >= 0:
                    self.fail[child], self.popped[child] = self.next[at][byte], taken
            queue += [(child, b, c) for b, c in self.next[child].items()]

    def _add(self, node: int, piece: bytes) -> int:
        for byte in piece:
            child = self.next[node].get(byte)
            if child is None:
                child = self.next[node][byte] = len(self.next)
                self.next.append({})
            node = child
        return node

    def count(self, word: bytes) -> int:
        """Pieces of a word that isn't empty; 0 if it can't be spelt."""
        following, fail, popped = self.next, self.fail, self.popped
        node = total = 0
        for byte in word:
            while (child := following[node].get(byte)) is None:
                total += popped[node]
                node = fail[node]
                if node < 0:
                    return 0
            node = child
        while node != 1:
            total += popped[node]
            node = fail[node]
            if node < 0:
                return 0
        return total


def from_ranks(path: str, spell_all: bool = False) -> Pieces:
    """Tokens with a leading blank start words, the others go on words.

    With ``spell_all`` single bytes start words too, so that words whose beginning
    has no token with a blank are spelt as well.
    """
    with open(path, "rb") as f:
        tokens = [base64.b64decode(line.split()[0]) for line in f if line.strip()]
    start = [t[1:] for t in tokens if t[:1] == b" "] + [t for t in tokens if spell_all and len(t) == 1]
    return Pieces(start, [t for t in tokens if t[:1] != b" "])


@cache
def pieces(path: str, spell_all: bool) -> tuple[Pieces, Recent]:
    """One a worker process."""
    return from_ranks(path, spell_all), Recent(CACHED_WORDS)


FIELDS = {c: ("bigint", pa.int64()) for c in ("n_words", "n_pieces", "n_unknown")}


def count_pieces(docs: DataFrame, path: str, *, text: str = "text", spell_all: bool = False) -> DataFrame:
    """``docs`` without the text, with n_words, n_pieces (unknown ones included) and n_unknown."""

    def each(raws: list[bytes]) -> list[list[int]]:
        automaton, cached = pieces(path, spell_all)
        rows = []
        with few_collections():
            cut = [raw.split() for raw in raws]
            counts, lacking = cached.known(set(chain.from_iterable(cut)))
            new = {w: automaton.count(w) for w in lacking}
            counts |= new
            cached.keep({w: c for w, c in new.items() if len(w) < LONG_WORD})
            for words in cut:
                counted = list(map(counts.__getitem__, words))
                unknown = counted.count(0)
                rows.append((len(counted), sum(counted) + unknown, unknown))
        return [[r[k] for r in rows] for k in range(3)]

    made = struct_of(FIELDS, each, lambda: pieces(path, spell_all)[1].rest())
    return with_results(docs, made(text_bytes(text)), list(FIELDS), without=(text,))
