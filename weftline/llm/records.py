"""Token ids as length-delimited binary records with an offset index.

A data file holds frames one after another:

    length   unsigned 64 bits, little-endian
    check    unsigned 32 bits: masked CRC-32 of the eight length bytes
    payload  length bytes
    check    unsigned 32 bits: masked CRC-32 of the payload

A checksum is masked by rotating it right by 15 bits and adding 0xa282ead8, so
that checksums stored inside checked data stay harmless.  The payload is the
document's id (signed 64 bits), a flags byte (1: the id is null; 2: ids of 16
bits instead of 32), the number of ids (unsigned 32 bits) and the ids.  Next to
each data file lies an index with the offset of every frame (unsigned 64 bits),
for shuffled reads.

Documents are dealt by ranges of their id, so the files in order hold them in
ascending order of id; a file is written under a name of its own and renamed,
so that a task that runs twice leaves one whole file.

Defined cases.  A null or empty text has the end id alone.  Rows that repeat an
id stay, in the order of their ids (ties in no set order); a null id comes first.
"""

from __future__ import annotations

import os
import struct
import uuid
import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import LOWER, Recent, column, few_collections, released, text_bytes
from .common import parts as texts_in_parts

MASK = 0xA282EAD8
HEAD = struct.Struct("<QI")
BODY = struct.Struct("<qBI")
CHECK = struct.Struct("<I")
#: All bytes of small Latin letters in UTF-8: a to z, and from 0xC3 on those of U+00DF to U+00FF but U+00F7.
LATIN = bytes([*range(97, 123), 0xC3, *range(0x9F, 0xB7), *range(0xB8, 0xC0)])
#: Line feeds to blanks, without and with ASCII capitals to small letters.
PLAIN_LINES = bytes(32 if b == 10 else b for b in range(256))
SMALL_LINES = bytes(32 if b == 10 else LOWER[b] for b in range(256))
#: Bytes of a frame besides its payload.
AROUND = HEAD.size + CHECK.size
NULL_ID, SHORT_IDS = 1, 2
CACHED_WORDS = 250_000
#: Words handed to the tokenizer as one text, and what stands between them: a
#: character that makes an id of its own wherever it stands between blanks.
JOINED_WORDS, BETWEEN = 500, b"\x01"
#: Bytes from which on a word isn't cached.
LONG_WORD = 64
#: Bytes of texts encoded at once.
BATCH_BYTES = 1 << 23


def masked(data: bytes) -> int:
    crc = zlib.crc32(data)
    return ((crc >> 15 | crc << 17) + MASK) & 0xFFFFFFFF


def frame(payload: bytes) -> bytes:
    length = struct.pack("<Q", len(payload))
    return b"".join((length, CHECK.pack(masked(length)), payload, CHECK.pack(masked(payload))))


def unframe(stream) -> Iterator[bytes]:
    """Payloads of a stream of frames; a wrong checksum or a short frame raises."""
    while head := stream.read(HEAD.size):
        if len(head) < HEAD.size:
            raise ValueError("a frame ends early")
        length, check = HEAD.unpack(head)
        if masked(head[:8]) != check:
            raise ValueError("a length doesn't match its checksum")
        rest = stream.read(length + CHECK.size)
        if len(rest) < length + CHECK.size:
            raise ValueError("a frame ends early")
        payload = rest[:length]
        if masked(payload) != CHECK.unpack(rest[length:])[0]:
            raise ValueError("a payload doesn't match its checksum")
        yield payload


def pack(doc_id: int | None, ids: bytes, short: bool) -> bytes:
    flags = NULL_ID * (doc_id is None) | SHORT_IDS * short
    return BODY.pack(doc_id or 0, flags, len(ids) // (2 if short else 4)) + ids


def unpack(payload: bytes) -> tuple[int | None, np.ndarray]:
    doc_id, flags, n = BODY.unpack_from(payload)
    kind = "<u2" if flags & SHORT_IDS else "<u4"
    return (None if flags & NULL_ID else doc_id), np.frombuffer(payload, kind, n, BODY.size).astype("<u4")


class WordEncoder:
    """The tokenizer applied to parts between blanks and line feeds, which it drops, cached.

    Words that aren't known go to the tokenizer many at once, with a separator
    between them whose id marks where the next one begins.  If the tokenizer makes
    small letters of capitals, the words' ASCII capitals are made small before and
    marks behind letters are set apart, so that fewer words differ, and words of
    Latin letters go without normalizer and pattern.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        self.tokenizer = Tokenizer.from_file(path)
        self.short = self.tokenizer.get_vocab_size() <= 1 << 16
        self.kind = "<u2" if self.short else "<u4"
        self.words = Recent(CACHED_WORDS)
        self.long: list[bytes] = []
        normal = self.tokenizer.normalizer
        self.smalls = normal is not None and normal.normalize_str("AZ az") == "az az"
        self.opening = {t.content[:2].encode() for t in self.tokenizer.get_added_tokens_decoder().values()}
        alone, between = (self._ids(t) for t in ("\x01", "a \x01 b"))
        ends = [*self._ids("a"), *alone, *self._ids("b")]
        self.between = alone[0] if len(alone) == 1 and between == ends else None
        self.light = self._light(path) if self.smalls else None

    def _light(self, path: str):
        """The tokenizer for small Latin letters, full stops and commas between blanks, if that gives the same ids.

        Normalizing leaves such words as they are, and the pattern matches each whole.
        """
        from tokenizers import Tokenizer, pre_tokenizers

        light = Tokenizer.from_file(path)
        light.normalizer = None
        bytes_alone = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        light.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), bytes_alone])
        letters = "abcdefghijklmnopqrstuvwxyzßàáâãäåæçèéêëìíîïðñòóôõöøùúûüýþÿ"
        words = [*letters, letters, letters[::-1], "word", "straße", "él"]
        for word in words:
            for tail in ("", ".", ","):
                if self._ids(word + tail) != light.encode(f"{word} {tail}", add_special_tokens=False).ids:
                    return None
        return light

    def _ids(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def _small(self, values: pa.Array) -> pa.Array:
        """The texts with line feeds as blanks and, where that changes no id, small ASCII letters and blanks between a letter and a mark."""
        ends = np.frombuffer(values.buffers()[1], np.int32)[values.offset : values.offset + len(values) + 1]
        raw = values.buffers()[2]
        raw = raw[int(ends[0]) : int(ends[-1])].to_pybytes() if raw else b""
        ends = ends - ends[0]
        table = SMALL_LINES if self.smalls else PLAIN_LINES
        text = raw.translate(table)
        if self.smalls and any(o in raw for o in self.opening):  # a token outside the vocabulary is matched as it is written
            whole = bytearray(text)
            for begin, end in zip(ends[:-1].tolist(), ends[1:].tolist()):
                part = raw[begin:end]
                if any(o in part for o in self.opening):
                    whole[begin:end] = part.translate(PLAIN_LINES)
            text = bytes(whole)
        if self.light is not None:
            at = np.frombuffer(text, np.uint8)
            marks = np.flatnonzero((at[1:-1] == 46) | (at[1:-1] == 44)) + 1
            marks = marks[(at[marks + 1] == 32) & (at[marks - 1] - np.uint8(97) < 26)]
            text = np.insert(at, marks, 32).tobytes()
            ends = ends + np.searchsorted(marks, ends)
        return pa.Array.from_buffers(pa.binary(), len(values), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(text)])

    def encode(self, values: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts (bytes, none null) one after another, and where each text's begin and end.

        Words are cut, numbered and put together again as Arrow columns; only distinct ones are Python values.
        """
        with few_collections():
            words = pc.split_pattern(self._small(values), " ")
            numbered = words.flatten().dictionary_encode()
            distinct = numbered.dictionary.to_pylist()
            coded = self.words.whole(set(distinct), self._made)
            codes = list(map(coded.__getitem__, distinct))
            for word in self.long:
                del coded[word]
            self.long.clear()
        width = np.dtype(self.kind).itemsize
        sizes = np.fromiter(map(len, codes), np.int64, len(codes)) // width
        ids = pa.array(np.frombuffer(b"".join(codes), self.kind))
        each = pa.LargeListArray.from_arrays(pa.array(np.append(0, np.cumsum(sizes))), ids)
        at = numbered.indices
        flat = each.take(at).flatten().to_numpy(zero_copy_only=False)
        ends = np.append(0, np.cumsum(sizes[at.to_numpy()]))
        return flat.astype(self.kind, copy=False), ends[words.offsets.to_numpy()]

    def _made(self, words: list[bytes]) -> dict[bytes, bytes]:
        self.long += [w for w in words if len(w) >= LONG_WORD]
        if self.between is None:
            return {w: np.array(self._ids(w.decode("utf-8", "replace")), self.kind).tobytes() for w in words}
        if self.light is None:
            return self._joined(words, self.tokenizer)
        rest = [w for w in words if w.translate(None, LATIN)]
        plain = [w for w in words if not w.translate(None, LATIN)]
        return self._joined(plain, self.light) | self._joined(rest, self.tokenizer)

    def _joined(self, words: list[bytes], tokenizer) -> dict[bytes, bytes]:
        """The ids of words, handed over many at once; those with the separator in them alone."""
        odd = [w for w in words if BETWEEN in w]
        new = {w: np.array(self._ids(w.decode("utf-8", "replace")), self.kind).tobytes() for w in odd}
        plain = [w for w in words if w not in new] if odd else words
        width = np.dtype(self.kind).itemsize
        for at in range(0, len(plain), JOINED_WORDS):
            some = plain[at : at + JOINED_WORDS]
            text = (b" " + BETWEEN + b" ").join(some).decode("utf-8", "replace")
            ids = np.array(tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, self.kind)
            ends = (np.flatnonzero(ids == self.between) * width).tolist()
            flat = ids.tobytes()
            begins = [0, *[e + width for e in ends]]
            new.update(zip(some, [flat[a:b] for a, b in zip(begins, [*ends, len(flat)], strict=True)], strict=True))
        return new


@cache
def word_encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


def opened(uri: str) -> tuple[pa.fs.FileSystem, str]:
    if uri.startswith("file:/") and not uri.startswith("file://"):
        uri = uri[len("file:") :]
    return pa.fs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}")


def write_whole(fs, path: str, parts: Iterator[bytes]) -> None:
    """A file that appears under its name only when it is whole."""
    own = f"{path}.{uuid.uuid4().hex}.tmp"
    try:
        with fs.open_output_stream(own) as out:
            for p in parts:
                out.write(p)
        fs.move(own, path)
    except BaseException:  # a task that fails or is killed leaves nothing behind
        if fs.get_file_info(own).type == pa.fs.FileType.File:
            fs.delete_file(own)
        raise


MANIFEST = "part int, path string, n_docs bigint, n_tokens bigint, bytes bigint"


def write_records(docs: DataFrame, tokenizer: str, folder: str, *, end_id: int = 2, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Writes ``docs`` under ``folder``; the manifest, a row per file, is what comes back."""

    def run(batches):
        coder = word_encoder(tokenizer)
        end = np.array([end_id], coder.kind).tobytes()
        part = TaskContext.get().partitionId()
        fs, root = opened(folder)
        path = f"{root}/part-{part:06d}.rec"
        counts, offsets = [0, 0, 0], []

        def frames() -> Iterator[bytes]:
            for batch in batches:
                ids, done = batch.column(0).to_pylist(), 0
                for some in texts_in_parts(batch.column(1), BATCH_BYTES):
                    flat, bounds = coder.encode(some)
                    bounds = bounds.tolist()
                    for doc, begin, stop in zip(ids[done : done + len(some)], bounds, bounds[1:]):
                        whole = frame(pack(doc, flat[begin:stop].tobytes() + end, coder.short))
                        offsets.append(counts[2])
                        counts[0] += 1
                        counts[1] += stop - begin + 1
                        counts[2] += len(whole)
                        yield whole
                    done += len(some)

        fs.create_dir(root, recursive=True)
        try:
            write_whole(fs, path, frames())
        finally:
            coder.words.rest(CACHED_WORDS // 2)
            released()
        write_whole(fs, f"{path}.idx", iter([np.array(offsets, "<u8").tobytes()]))
        yield pa.RecordBatch.from_pylist([
            {"part": part, "path": f"{folder}/part-{part:06d}.rec", "n_docs": counts[0], "n_tokens": counts[1], "bytes": counts[2]}
        ], pa.schema([("part", pa.int32()), ("path", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64()), ("bytes", pa.int64())]))

    ranged = docs.select(column(doc_id).cast("bigint").alias("doc_id"), text_bytes(text).alias("text"))
    ranged = ranged.repartitionByRange("doc_id").sortWithinPartitions("doc_id")
    return ranged.mapInArrow(run, MANIFEST)


READ = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint, path string, offset bigint"


def read_records(spark: SparkSession, manifest: list, *, ids: bool = False) -> DataFrame:
    """Every record of the files, with the number of ids before it in all of them.

    ``manifest`` has a row a file, some hundred bytes; a file goes to one task, as a stream.
    """
    before, rows = 0, []
    for m in sorted(manifest, key=lambda m: m["part"]):
        rows.append((m["path"], before))
        before += m["n_tokens"]
    schema = READ + (", token_ids array<int>" if ids else "")

    def run(batches):
        for batch in batches:
            for path, start in zip(*[c.to_pylist() for c in batch.columns]):
                fs, at = opened(path)
                out, held, offset = columns(ids), 0, 0
                with fs.open_input_stream(at, buffer_size=1 << 20) as stream:
                    for payload in unframe(stream):
                        doc, found = unpack(payload)
                        for kept, value in zip(out, (doc, start, len(found), zlib.crc32(found), path, offset, found)):
                            kept.append(value)
                        held += len(found) if ids else 0
                        start += len(found)
                        offset += len(payload) + AROUND
                        if len(out[0]) >= 4096 or held >= 1 << 21:
                            yield to_batch(out, ids)
                            out, held = columns(ids), 0
                if out[0]:
                    yield to_batch(out, ids)

    files = spark.createDataFrame(rows, "path string, start bigint")
    return files.repartition(max(1, len(rows))).mapInArrow(run, schema)


def columns(ids: bool) -> list[list]:
    return [[] for _ in range(7 if ids else 6)]


def to_batch(out: list[list], ids: bool) -> pa.RecordBatch:
    fields = [("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64()), ("path", pa.string()), ("offset", pa.int64())]
    fields += [("token_ids", pa.list_(pa.int32()))] if ids else []
    if ids:
        out[6] = [found.astype("<i4") for found in out[6]]
    return pa.RecordBatch.from_arrays([pa.array(c, kind) for c, (_, kind) in zip(out, fields)], schema=pa.schema(fields))


def read_at(path: str, places: list[int]) -> Iterator[tuple[int | None, np.ndarray]]:
    """Records by their places in the file, in any order, through its index."""
    fs, at = opened(path)
    with fs.open_input_file(f"{at}.idx") as index, fs.open_input_file(at) as data:
        for k in places:
            index.seek(8 * k)
            data.seek(struct.unpack("<Q", index.read(8))[0])
            yield unpack(next(unframe(data)))
