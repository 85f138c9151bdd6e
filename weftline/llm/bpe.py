"""Byte-level BPE, encoding and decoding, on segment trees.

A piece (one match of the pattern) starts as single bytes.  Leaf ``i`` of its
segment tree holds the rank of the pair that begins at byte ``i`` together with
``i``, so the root is the leftmost pair of least rank; a merge overwrites three
leaves (the pair, its left neighbour, the byte swallowed) and their paths.  The
trees of many distinct pieces are worked as one array, long pieces singly.

A word with its leading blank is encoded once per worker and kept in a cache of
bounded size; cutting at single blanks between other characters never changes
the matches of the pattern, and any other white space goes through the pattern.

Defined cases.  A null or empty text has no ids; decoding gives zero bytes.
Repeated rows are encoded alike.  Extra columns pass through whatever their
names, those named like the results are replaced.  A piece may be of any length.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator
from functools import cache
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Recent, column, few_collections, free_name, in_pieces, struct_of, with_results

#: Code points with the White_Space property but the line feed and the blank.
OTHER_SPACE = "\t\x0b\x0c\r\x85\xa0  -     　"
SPACE = f"\n {OTHER_SPACE}"

NONE = np.int64(1) << 62
#: Bits of a position in a piece under LONE_LEAVES; a longer piece takes as many as its length needs.
POSITION_BITS = 24
#: Leaves from which a piece gets a tree of its own.
LONE_LEAVES = 256
#: Entries that a cache keeps at most, twice over, and length from which on it keeps none.
CACHED_WORDS, LONG_WORD = 200_000, 64
#: Bytes of texts encoded at once.
BATCH_BYTES = 1 << 23


class Ranks:
    """A vocabulary file of ranks with the ranks of all pairs of its tokens."""

    def __init__(self, path: str):
        with open(path, "rb") as f:
            self.ids = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.tokens = [b""] * (max(self.ids.values()) + 1)
        for token, at in self.ids.items():
            self.tokens[at] = token
        self.of_byte = np.array([self.ids.get(bytes([b]), -1) for b in range(256)], np.int64)
        if (self.of_byte < 0).any():
            raise ValueError("every single byte needs a rank")
        self.pairs = {
            self.ids[token[:k]] << 32 | self.ids[token[k:]]: at
            for token, at in self.ids.items()
            for k in range(1, len(token))
            if token[:k] in self.ids and token[k:] in self.ids
        }
        self.keys = np.array(sorted(self.pairs), np.int64)
        self.values = np.array([self.pairs[k] for k in self.keys.tolist()], np.int64)

    def of_pairs(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Ranks of the pairs of ids, -1 for none; negative ids have none."""
        key = left << 32 | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where((self.keys[at] == key) & (left >= 0) & (right >= 0), self.values[at], -1)


def leaf(rank: np.ndarray, at: np.ndarray) -> np.ndarray:
    return np.where(rank >= 0, rank << POSITION_BITS | at, NONE)


def encode_forest(pieces: list[bytes], width: int, ranks: Ranks) -> list[bytes]:
    """Ids of pieces of at most ``width`` bytes, as little-endian 32-bit integers."""
    n = len(pieces)
    size = np.fromiter(map(len, pieces), np.int64, n)
    column = np.arange(width)
    live = column < size[:, None]
    ids = np.full((n, width), -1, np.int64)
    ids[live] = ranks.of_byte[np.frombuffer(b"".join(pieces), np.uint8)]
    after = np.where(column + 1 < size[:, None], column + 1, width)
    before = np.broadcast_to(column - 1, (n, width)).copy()
    tree = np.full((n, 2 * width), NONE, np.int64)
    tree[:, width : 2 * width - 1] = leaf(ranks.of_pairs(ids[:, :-1], ids[:, 1:]), column[:-1])
    level = width >> 1
    while level:
        tree[:, level : 2 * level] = np.minimum(tree[:, 2 * level : 4 * level : 2], tree[:, 2 * level + 1 : 4 * level : 2])
        level >>= 1
    row = np.flatnonzero(tree[:, 1] < NONE)
    while len(row):
        top = tree[row, 1]
        at, new = top & ((1 << POSITION_BITS) - 1), top >> POSITION_BITS
        gone = after[row, at]
        right = after[row, gone]
        left = before[row, at]
        ids[row, at] = new
        ids[row, gone] = -1
        after[row, at] = right
        has = right < width
        before[row[has], right[has]] = at[has]
        tree[row, width + gone] = NONE
        tree[row, width + at] = leaf(np.where(has, ranks.of_pairs(new, ids[row, np.minimum(right, width - 1)]), -1), at)
        some = left >= 0
        r, p = row[some], left[some]
        tree[r, width + p] = leaf(ranks.of_pairs(ids[r, p], new[some]), p)
        for who, node in ((row, width + gone), (row, width + at), (r, width + p)):
            up = node >> 1
            while up[0:1].any():
                tree[who, up] = np.minimum(tree[who, 2 * up], tree[who, 2 * up + 1])
                up = up >> 1
        row = row[tree[row, 1] < NONE]
    ends = np.cumsum((ids >= 0).sum(1)) * 4
    flat = ids[ids >= 0].astype("<u4").tobytes()
    return [flat[a:b] for a, b in zip([0, *ends.tolist()], ends.tolist())]


def encode_lone(piece: bytes, ranks: Ranks) -> bytes:
    """The same on one tree, for long pieces."""
    n = len(piece)
    width = 1 << max(1, (n - 1).bit_length())
    bits = n.bit_length()
    pairs, none = ranks.pairs, 1 << 32 + bits
    ids = ranks.of_byte[np.frombuffer(piece, np.uint8)].tolist()
    after, before = [*range(1, n + 1)], [*range(-1, n - 1)]
    tree = [none] * (2 * width)

    def put(at: int, value: int) -> None:
        at += width
        tree[at] = value
        while at > 1:
            at >>= 1
            tree[at] = min(tree[2 * at], tree[2 * at + 1])

    def pair(at: int) -> int:
        if at < 0 or after[at] >= n:
            return none
        rank = pairs.get(ids[at] << 32 | ids[after[at]])
        return none if rank is None else rank << bits | at

    tree[width : width + n] = map(pair, range(n))
    for node in range(width - 1, 0, -1):
        tree[node] = min(tree[2 * node], tree[2 * node + 1])
    while tree[1] < none:
        at = tree[1] & ((1 << bits) - 1)
        gone = after[at]
        ids[at], ids[gone] = tree[1] >> bits, -1
        after[at] = after[gone]
        if after[at] < n:
            before[after[at]] = at
        put(gone, none)
        put(at, pair(at))
        if before[at] >= 0:
            put(before[at], pair(before[at]))
    return np.array([x for x in ids if x >= 0], "<u4").tobytes()


def encode_pieces(pieces: list[bytes], ranks: Ranks) -> dict[bytes, bytes]:
    found, classes = {}, {}
    for piece in pieces:
        whole = ranks.ids.get(piece)
        if whole is not None:
            found[piece] = whole.to_bytes(4, "little")
        elif len(piece) >= LONE_LEAVES:
            found[piece] = encode_lone(piece, ranks)
        else:
            classes.setdefault(1 << max(1, (len(piece) - 1).bit_length()), []).append(piece)
    for width, some in classes.items():
        for part in in_pieces(some, lambda _: width, 1 << 18):
            found.update(zip(part, encode_forest(part, width, ranks)))
    return found


class Encoder:
    """Encodes texts by ranks, a pattern and caches of bounded size."""

    def __init__(self, path: str, pattern: str):
        self.ranks = Ranks(path)
        told = pattern.replace(r"[^\s", f"[^{SPACE}").replace(r"\S", f"[^{SPACE}]").replace(r"\s", f"[{SPACE}]")
        self.pieces = regex.compile(told).findall
        self.odd = re.compile(f"[{OTHER_SPACE}]|[ \n] | \n|^ | $").search
        self.cut = re.compile(f"(?<=[^{SPACE}])(?= [^{SPACE}])").split
        self.words = Recent(CACHED_WORDS)
        self.parts = Recent(CACHED_WORDS)

    def chunks(self, text: str) -> list[str]:
        """The text in parts that the pattern matches separately; a part but the first starts with a blank."""
        if self.odd(text):
            return self.cut(text)
        first, *rest = text.split(" ")
        return [first, *map(" ".__add__, rest)] if first or rest else []

    def encode(self, texts: list[str]) -> list[bytes]:
        """Per text its ids as little-endian 32-bit integers."""
        with few_collections():
            cut = [self.chunks(t) for t in texts]
            coded, lacking = self.words.known(set(chain.from_iterable(cut)))
            if lacking:
                pieces = [[p.encode() for p in self.pieces(c)] for c in lacking]
                parts, unknown = self.parts.known(set(chain.from_iterable(pieces)))
                fresh = encode_pieces(unknown, self.ranks)
                parts |= fresh
                new = {c: b"".join(map(parts.__getitem__, ps)) for c, ps in zip(lacking, pieces)}
                coded |= new
                self.parts.keep({p: v for p, v in fresh.items() if len(p) < LONG_WORD})
                self.words.keep({c: v for c, v in new.items() if len(c) < LONG_WORD})
            return [b"".join(map(coded.__getitem__, chunks)) for chunks in cut]

    def rest(self) -> None:
        """Leaves small caches to the worker's next task."""
        self.words.rest()
        self.parts.rest()

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.ranks.tokens.__getitem__, np.frombuffer(ids, "<u4").tolist()))


@cache
def encoder(path: str, pattern: str) -> Encoder:
    """One a worker process."""
    return Encoder(path, pattern)


def encode(docs: DataFrame, path: str, pattern: str, *, text: str = "text", ids: bool = True, digests: bool = True) -> DataFrame:
    """``docs`` without the text, with n_tokens and, as asked, token_ids and digests of ids and decoded bytes."""
    fields = {"n_tokens": ("bigint", pa.int64())}
    if ids:
        fields["token_ids"] = ("array<int>", pa.list_(pa.int32()))
    if digests:
        fields |= {"ids_sha256": ("string", pa.string()), "decoded_sha256": ("string", pa.string())}

    def each(texts: list[str]) -> list:
        bpe = encoder(path, pattern)
        coded = bpe.encode(texts)
        lengths = [len(c) // 4 for c in coded]
        out: list = [lengths]
        if ids:
            flat = np.frombuffer(b"".join(coded), "<i4")
            out.append(pa.ListArray.from_arrays(pa.array(np.cumsum([0, *lengths]).astype(np.int32)), pa.array(flat, pa.int32())))
        if digests:
            out.append([hashlib.sha256(c).hexdigest() for c in coded])
            out.append([hashlib.sha256(bpe.decode(c)).hexdigest() for c in coded])
        return out

    made = struct_of(fields, each, lambda: encoder(path, pattern).rest(), BATCH_BYTES)
    return with_results(docs, made(F.coalesce(column(text), F.lit(""))), list(fields), without=(text,))


def decode(coded: DataFrame, path: str, pattern: str, *, ids: str = "token_ids") -> DataFrame:
    """``coded`` with ``text_bytes``, the bytes that the ids stand for."""
    result = free_name(coded, "made")

    def joined(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        tokens = encoder(path, pattern).ranks.tokens
        for batch in batches:
            yield pa.array([b"".join(map(tokens.__getitem__, r or ())) for r in batch.to_pylist()], pa.binary())

    made = F.arrow_udf(joined, "binary")(column(ids))
    own = [column(c) for c in coded.columns if c.lower() != "text_bytes"]
    return coded.withColumn(result, made).select(*own, column(result).alias("text_bytes"))
