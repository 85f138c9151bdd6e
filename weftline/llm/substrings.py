"""Substring dedup with automata of repeated phrases.

A window is a run of ``size`` words of one document.  Words go that lie in a
window whose words also start in a document of smaller id.

1. Candidates.  Of each window the least hash of its ``ANCHOR``-word runs is its
   anchor; equal windows have equal anchors, and about one word in 18 begins one.
   Anchors of one document alone end the matter for nearly all text.
2. Confirmation.  Windows at recurring anchors are grouped by their own hashes;
   those of two or more documents are recurring, and the document of least id
   that has one is its home (of smaller id than all others that have it).  Runs of
   such windows in a home are passages.
   Whole copies of a text are found by a digest first and have one home, too.
3. Location.  Passages are dealt to shards of bounded size.  A shard compiles an
   Aho-Corasick automaton (pyahocorasick) over aligned blocks of half a window,
   one character standing for a distinct word, and streams the documents that
   are confirmed to share windows with its homes, against those homes; each hit
   is extended word by word in both directions.  Any window inside a passage holds a whole block, so
   every occurrence is located, and by the words themselves, not by hashes.
   Shards with many documents are salted.  A home that repeats itself (one block
   at many places), where each hit would have to be tried at every place, or
   that has more distinct words than there are characters is searched by 128-bit
   digests of its windows instead, in time linear in the document.

Defined cases.  A null or empty text has no words.  ``doc_id`` identifies a
document: rows that repeat it are taken to repeat its text.  A document without
an id is kept whole and removes nothing.  Texts may be of any length and repeat
one word throughout.  Extra columns of any name pass through.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column, dropped, free_name, parts, releasing, stored, text_bytes

WINDOW, ANCHOR = 50, 16
#: Passage words to a shard, about, and bytes of documents to one of its tasks.
SHARD_WORDS = 150_000
SALT_BYTES = 16 << 20
#: Places of one block in a home from which on its windows are looked up by digests.
MANY_PLACES = 32
#: Distinct words that a shard has characters for.
MOST_CODES = 1_100_000

BASE = np.uint64(0xD6E8FEB86659FD93)
SECOND = np.uint64(0xA0761D6478BD642F)
INVERSES = {int(b): np.uint64(pow(int(b), -1, 1 << 64)) for b in (BASE, SECOND)}


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[:1] = 1
    return np.multiply.accumulate(out)


def run_hashes(words: np.ndarray, size: int, base: np.uint64 = BASE) -> np.ndarray:
    """A hash for every run of ``size`` words, from sums of powers, mixed at the end."""
    n = len(words)
    if n < size:
        return np.empty(0, np.uint64)
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum(words * powers(INVERSES[int(base)], n), out=sums[1:])
    out = (sums[size:] - sums[:-size]) * powers(base, n - size + 1)
    out ^= out >> np.uint64(32)
    out *= np.uint64(0xFF51AFD7ED558CCD)
    return out ^ out >> np.uint64(29)


def window_anchors(words: np.ndarray, size: int) -> np.ndarray:
    """Per window the least hash of its anchor runs."""
    low = run_hashes(words, ANCHOR)
    width, have = size - ANCHOR + 1, 1
    if len(low) < width:
        return np.empty(0, np.uint64)
    while 2 * have <= width:
        low = np.minimum(low[:-have], low[have:])
        have *= 2
    return np.minimum(low[: len(low) - (width - have)], low[width - have :])


SCAN = "id bigint, n_words bigint, sha string, copy_a bigint, copy_b bigint, anchors array<bigint>"


def scan(source: DataFrame, size: int) -> DataFrame:
    """Per document its words' number and digests and its distinct anchors."""

    def run(batches):
        for batch in batches:
            rows, flat, ends = [], [], [0]
            for raw in (raw for part in parts(batch.column(1)) for raw in part.to_pylist()):
                words = raw.split()
                joined = b" ".join(words)
                copy = xxhash.xxh3_128_intdigest(joined)
                low = window_anchors(word_hashes(words), size) if len(words) >= size else np.empty(0, np.uint64)
                if len(low):
                    low = np.unique(low[np.append(True, low[1:] != low[:-1])])
                flat.append(low)
                ends.append(ends[-1] + len(low))
                rows.append((len(words), hashlib.sha256(joined).hexdigest(), copy >> 64, copy & (1 << 64) - 1))
            copies = np.array([r[2:] for r in rows], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows]),
                 pa.array(copies[:, 0]), pa.array(copies[:, 1]),
                 pa.ListArray.from_arrays(pa.array(np.array(ends, np.int32)), pa.array(np.concatenate(flat).view(np.int64)))],
                ["id", "n_words", "sha", "copy_a", "copy_b", "anchors"],
            )

    return source.mapInArrow(releasing(run), SCAN)


def anchored_windows(texts: DataFrame, size: int) -> DataFrame:
    """Windows whose anchor is among the document's recurring ones: two hashes, id, place."""

    def run(batches):
        for batch in batches:
            for doc, raw, anchors in zip(*[c.to_pylist() for c in batch.columns]):
                words = word_hashes(raw.split())
                known = np.sort(np.array(anchors, np.int64).view(np.uint64))
                low = window_anchors(words, size)
                at = np.minimum(np.searchsorted(known, low), len(known) - 1)
                places = np.flatnonzero(known[at] == low)
                first, second = (run_hashes(words, size, b)[places].view(np.int64) for b in (BASE, SECOND))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(first), pa.array((second >> 32).astype(np.int32)), pa.array(np.full(len(places), doc, np.int64)), pa.array(places.astype(np.int32))],
                    ["h", "h2", "id", "at"],
                )

    return texts.mapInArrow(releasing(run), "h bigint, h2 int, id bigint, at int")


def runs(places: list[int], size: int) -> list[tuple[int, int]]:
    """Word ranges that windows at these places cover, those with a common word as one."""
    out: list[tuple[int, int]] = []
    for at in sorted(places):
        if out and at <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], at + size))
        else:
            out.append((at, at + size))
    return out


def ahead(a: str, i: int, b: str, j: int) -> int:
    """Length of the common run of ``a`` from i and ``b`` from j."""
    most = min(len(a) - i, len(b) - j)
    have, step = 0, 32
    while have < most:
        step = min(step, most - have)
        if a[i + have : i + have + step] == b[j + have : j + have + step]:
            have += step
            step *= 2
        elif step == 1:
            break
        else:
            step = max(1, step // 4)
    return have


def window_digests(words: list[bytes], size: int) -> Iterator[int]:
    """A 128-bit digest of each window."""
    return (xxhash.xxh3_128_intdigest(b" ".join(words[at : at + size])) for at in range(len(words) - size + 1))


class Phrases:
    """The automaton of one shard; a character stands for a distinct word."""

    def __init__(self, passages: list[tuple[int, bytes]], size: int):
        self.size, self.block = size, size // 2
        self.codes: dict[bytes, str] = {}
        coded = [self._coded(raw.split()) for _, raw in passages]
        many = {home for (home, _), text in zip(passages, coded) if text is None}
        places: dict[str, dict[int, list[tuple[int, int]]]] = {}
        for k, ((home, _), text) in enumerate(zip(passages, coded)):
            for at in range(0, len(text or "") - self.block + 1, self.block):
                places.setdefault(text[at : at + self.block], {}).setdefault(home, []).append((k, at))
        for found in places.values():
            many |= {home for home, at in found.items() if len(at) > MANY_PLACES}
        self.digests = {home: set() for home in many}
        for home, raw in passages:
            if home in many:
                self.digests[home].update(window_digests(raw.split(), size))
        for phrase, found in list(places.items()):
            for home in many & found.keys():
                del found[home]
            if not found:
                del places[phrase]
        self.passages = ["" if home in many else text for (home, _), text in zip(passages, coded)]
        self.backward = [text[::-1] for text in self.passages]
        self.automaton = ahocorasick.Automaton()
        for phrase, found in places.items():
            self.automaton.add_word(phrase, found)
        self.passages_coded = bool(places)
        self.automaton.make_automaton()

    def _coded(self, words: list[bytes]) -> str | None:
        codes = self.codes
        if len(codes) + len(words) > MOST_CODES and len(codes) + len(set(words) - codes.keys()) > MOST_CODES:
            return None
        for w in words:
            if w not in codes:
                n = len(codes) + 1
                codes[w] = chr(n if n < 0xD800 else n + 0x800)
        return "".join(map(codes.__getitem__, words))

    def find(self, raw: bytes, homes: list[int]) -> list[tuple[int, int]]:
        """Disjoint ranges of words of the text that passages of these homes cover."""
        get, words = self.codes.get, raw.split()
        text = "".join([get(w, "\0") for w in words])
        back, n = text[::-1], len(text)
        found: list[tuple[int, int]] = []
        done: dict[tuple[int, int], int] = {}
        mine = set(homes)
        if repetitive := mine & self.digests.keys():
            mine -= repetitive
            known = [self.digests[home] for home in repetitive]
            found = runs([at for at, d in enumerate(window_digests(words, self.size)) if any(d in k for k in known)], self.size)
        for end, places in self.automaton.iter(text) if mine and self.passages_coded else ():
            begin = end - self.block + 1
            few, many = (mine, places) if len(mine) < len(places) else (places, mine)
            for home in few:
                if home not in many:
                    continue
                for k, at in places[home]:
                    if done.get((k, begin - at), -1) > begin:
                        continue
                    passage = self.passages[k]
                    right = begin + ahead(text, begin, passage, at)
                    left = begin - ahead(back, n - begin, self.backward[k], len(passage) - at)
                    done[k, begin - at] = right
                    if right - left >= self.size:
                        found.append((left, right))
                        if right - left == n:
                            return [(0, n)]
        merged: list[tuple[int, int]] = []
        for left, right in sorted(found):
            if merged and left <= merged[-1][1]:
                merged[-1] = (merged[-1][0], max(merged[-1][1], right))
            else:
                merged.append((left, right))
        return merged


def located(rows: DataFrame, size: int) -> DataFrame:
    """id, begin, end from rows (shard, salt, kind 0 passage or 1 document, id, homes, raw)."""

    def run(batches):
        key, passages, phrases = None, [], None
        for batch in batches:
            out = []
            for shard, salt, kind, doc, homes, raw in zip(*[c.to_pylist() for c in batch.columns]):
                if (shard, salt) != key:
                    key, passages, phrases = (shard, salt), [], None
                if kind == 0:
                    passages.append((doc, raw))
                else:
                    if phrases is None:
                        phrases = Phrases(passages, size)
                    out += [(doc, begin, end) for begin, end in phrases.find(raw, homes)]
            yield pa.RecordBatch.from_arrays(
                [pa.array([r[0] for r in out], pa.int64()), *[pa.array([r[k] for r in out], pa.int32()) for k in (1, 2)]],
                ["id", "begin", "end"],
            )

    own = ["shard", "salt"]
    dealt = rows.repartition(*own).sortWithinPartitions(*own, "kind", "id")
    return dealt.select(*own, "kind", "id", "homes", "raw").mapInArrow(releasing(run), "id bigint, begin int, end int")


def passages_of(homes: DataFrame, size: int) -> DataFrame:
    """Word ranges of homes as texts; homes: home, whole, places, raw."""

    def run(batches):
        for batch in batches:
            out = []
            for home, whole, places, raw in zip(*[c.to_pylist() for c in batch.columns]):
                words = raw.split()
                spans = [(0, len(words))] if whole else runs(places or [], size)
                out += [(home, b" ".join(words[a:b])) for a, b in spans]
            yield pa.RecordBatch.from_arrays(
                [pa.array([r[0] for r in out], pa.int64()), pa.array([r[1] for r in out], pa.binary())], ["home", "raw"]
            )

    return homes.select("home", "whole", "places", "raw").mapInArrow(releasing(run), "home bigint, raw binary")


def kept_texts(covered: DataFrame) -> DataFrame:
    """id, n_removed, kept_sha256, kept from id, spans, raw."""

    def run(batches):
        for batch in batches:
            out = []
            for doc, spans, raw in zip(*[c.to_pylist() for c in batch.columns]):
                words, left, end = raw.split(), [], 0
                n = len(words)
                for begin, stop in sorted((s["begin"], s["end"]) for s in spans):
                    if begin > end:
                        left += words[end:begin]
                    end = max(end, stop)
                left += words[end:]
                joined = b" ".join(left)
                out.append((doc, n - len(left), hashlib.sha256(joined).hexdigest(), joined.decode("utf-8", "replace")))
            yield pa.RecordBatch.from_arrays(
                [pa.array([r[k] for r in out], kind) for k, kind in enumerate((pa.int64(), pa.int64(), pa.string(), pa.string()))],
                ["id", "n_removed", "kept_sha256", "kept"],
            )

    return covered.select("id", "spans", "raw").mapInArrow(releasing(run), "id bigint, n_removed bigint, kept_sha256 string, kept string")


def find_repeats(source: DataFrame, size: int = WINDOW) -> tuple[DataFrame, DataFrame]:
    """Of source (id, raw): the scan of every row, and id, spans, raw of documents that lose words."""
    if size <= ANCHOR:
        raise ValueError(f"a window needs more than {ANCHOR} words")
    scanned = stored(scan(source, size), "scan")
    long_enough = scanned.filter((F.col("n_words") >= size) & F.col("id").isNotNull())
    copies = long_enough.groupBy("copy_a", "copy_b").agg(F.min("id").alias("first"), F.max("id").alias("last"), F.first("anchors").alias("anchors"))
    groups = long_enough.groupBy("copy_a", "copy_b").agg(F.min("id").alias("first"), F.max("id").alias("last")).filter("first < last")
    twins = stored(
        long_enough.select("id", "copy_a", "copy_b").join(groups, ["copy_a", "copy_b"]).select("id", F.col("first").alias("home")), "twins"
    )

    # candidates: anchors of two or more distinct texts
    anchors = copies.select(F.col("first").alias("id"), F.explode("anchors").alias("anchor"))
    spread = anchors.groupBy("anchor").agg(F.min("id").alias("low"), F.max("id").alias("high"))
    recurring = stored(spread.filter("low < high").select("anchor"), "anchors")
    flagged = anchors.join(recurring, "anchor").groupBy("id").agg(F.collect_list("anchor").alias("anchors"))
    needed = flagged.unionByName(twins.select("id", F.array().cast("array<bigint>").alias("anchors"))).groupBy("id").agg(
        F.flatten(F.collect_list("anchors")).alias("anchors")
    )
    texts = stored(source.join(needed, "id").dropDuplicates(["id"]).select("id", "raw", "anchors"), "texts")

    # confirmation: windows of two or more distinct texts and their homes
    windows = anchored_windows(texts.filter(F.size("anchors") > 0), size)
    firsts = windows.groupBy("h", "h2").agg(F.min("id").alias("home"), F.max("id").alias("last"))
    # tables like this one make both sides of a join plain, so that adaptive execution splits a key of very many documents
    shared = stored(firsts.filter("home < last").select("h", "h2", "home"), "windows")
    confirmed = windows.join(shared, ["h", "h2"]).groupBy("id", "home").agg(
        F.collect_set(F.when(F.col("id") == F.col("home"), F.col("at"))).alias("places")
    )
    pairs = stored(confirmed, "confirmed")
    dropped(shared, recurring)
    homes = pairs.filter("id = home").select("home", F.lit(False).alias("whole"), "places").unionByName(
        twins.filter("id = home").distinct().select("home", F.lit(True).alias("whole"), F.array().cast("array<int>").alias("places"))
    )
    uses = pairs.filter("id <> home").select("id", "home").unionByName(twins.filter("id <> home")).distinct()

    # location: automata of the shards over the documents routed to them
    raw = texts.select(F.col("id").alias("home"), "raw")
    passages = stored(passages_of(homes.join(raw, "home"), size), "passages")
    volume = passages.agg(F.sum(F.octet_length("raw"))).first()[0] or 0
    n_shards = max(1, -(-volume // (6 * SHARD_WORDS)))
    shard = F.pmod(F.xxhash64("home"), F.lit(n_shards)).alias("shard")
    asked = stored(uses.groupBy("id", shard).agg(F.collect_set("home").alias("homes")), "asked")
    routed = asked.join(texts.select("id", "raw"), "id")
    salts = stored(
        asked.select("id", "shard").join(texts.select("id", F.octet_length("raw").alias("bytes")), "id")
        .groupBy("shard").agg(F.greatest(F.lit(1), F.ceil(F.sum("bytes") / SALT_BYTES)).cast("int").alias("salts")),
        "salts",
    )
    asking = routed.join(salts, "shard").select(
        "shard", F.pmod(F.xxhash64("id"), "salts").cast("int").alias("salt"), F.lit(1).alias("kind"), "id", "homes", "raw"
    )
    known = passages.select(shard, F.col("home").alias("id"), "raw").join(salts, "shard").select(
        "shard", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.lit(0).alias("kind"), "id", F.array().cast("array<bigint>").alias("homes"), "raw"
    )
    spans = located(known.unionByName(asking), size).groupBy("id").agg(F.collect_list(F.struct("begin", "end")).alias("spans"))
    return scanned, spans.join(texts.select("id", "raw"), "id")


def sources(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    return docs.select(column(doc_id).cast("bigint").alias("id"), text_bytes(text).alias("raw"))


def repeat_digests(docs: DataFrame, size: int = WINDOW, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_words, n_removed and kept_sha256 of every row."""
    scanned, covered = find_repeats(sources(docs, doc_id, text), size)
    left = kept_texts(covered).drop("kept")
    return scanned.join(left, "id", "left").select(
        F.col("id").alias("doc_id"), "n_words", F.coalesce("n_removed", F.lit(0).cast("bigint")).alias("n_removed"),
        F.coalesce("kept_sha256", "sha").alias("kept_sha256"),
    )


def remove_repeats(docs: DataFrame, size: int = WINDOW, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` without the repeated words; documents that lose every word go, untouched ones keep their texts."""
    _, covered = find_repeats(sources(docs, doc_id, text), size)
    left = kept_texts(covered).select(F.struct("id", "kept").alias(free_name(docs, "left")))
    of = column(left.columns[0])
    joined = docs.join(left, column(doc_id) == of["id"], "left").filter(of["kept"].isNull() | (of["kept"] != ""))
    return joined.select(*[F.coalesce(of["kept"], column(c)).alias(c) if c == text else column(c) for c in docs.columns])
