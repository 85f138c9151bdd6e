"""WARC archives: written from page rows, read back in splits by boundary chains.

Records are written uncompressed, one file a task.  A payload that an earlier
page (by id) already has becomes a revisit record that names that page.

A reader's task gets a range of bytes of a file.  Each place there with the
magic line and a parsable header is a candidate, also where a payload holds a
whole record as text; the candidate names its successor, the byte after its
block.  Following successors inside its range, a task gives for each candidate
the first place beyond the range.  Pointer jumping over these steps, from byte 0
of each file, finds the one true entry of every range; from there the records
are read, so magic inside payloads is never taken for a record.

Defined cases.  A null html is an empty payload; a null id or URL is written as
such.  Rows that repeat a page id each keep a record; the smallest id is the
response, and of its repeated rows every one is.  Empty tables give no files.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import scratch, stored
from .records import opened, write_whole

MAGIC = b"WARC/1.1\r\n"
SPLIT_BYTES = 8 << 20
READ_BYTES = 1 << 20
HEADER_BYTES = 1 << 12
#: Groups of equal payloads up to which their table is broadcast, some 20 MB.
BROADCAST_GROUPS = 200_000


def header(fields: list[tuple[str, str]], length: int) -> bytes:
    lines = [f"{k}: {v}" for k, v in fields] + [f"Content-Length: {length}"]
    return MAGIC + "\r\n".join(lines).encode() + b"\r\n\r\n"


def record(page_id: int | None, url: str | None, html: bytes, first: int | None) -> bytes:
    """A response record, or a revisit (without a block) if ``first`` is given."""
    digest = base64.b32encode(hashlib.sha1(html).digest()).decode()
    target = re.sub(r"[\x00-\x20]+", "%20", url) if url is not None else ""
    fields = [
        ("WARC-Type", "response" if first is None else "revisit"),
        ("WARC-Record-ID", f"<urn:page:{'' if page_id is None else page_id}>"),
        ("WARC-Target-URI", target),
        ("WARC-Payload-Digest", f"sha1:{digest}"),
        ("X-Payload-Bytes", str(len(html))),
    ]
    if first is not None:
        fields += [("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Refers-To", f"<urn:page:{first}>")]
        html = b""
    return header(fields, len(html)) + html + b"\r\n\r\n"


def with_first(pages: DataFrame, least_bytes: int) -> DataFrame:
    """``pages`` (page_id, url, html) with ``first``: the smallest id of an equal payload, for revisits."""
    html = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    digested = pages.select(F.col("page_id").cast("bigint").alias("page_id"), "url", html.alias("html")).withColumns(
        {"_sha": F.sha1("html"), "_n": F.octet_length("html")}
    )
    shared = stored(
        digested.filter(F.col("_n") >= least_bytes).groupBy("_sha", "_n")
        .agg(F.min("page_id").alias("first"), F.count("*").alias("_rows")).filter("_rows > 1").drop("_rows"),
        "payloads",
    )
    few = shared.count() <= BROADCAST_GROUPS
    joined = digested.join(F.broadcast(shared) if few else shared, ["_sha", "_n"], "left")
    is_first = F.col("page_id").eqNullSafe(F.col("first"))
    return joined.select("page_id", "url", "html", F.when(~is_first, F.col("first")).alias("first"))


MANIFEST = "path string, bytes bigint, records bigint"


def write_warc(pages: DataFrame, folder: str, *, least_bytes: int = 0) -> DataFrame:
    """Writes the pages' records under ``folder``; the manifest comes back, a row a file."""

    def run(batches):
        fs, root = opened(folder)
        name = f"part-{TaskContext.get().partitionId():06d}.warc"
        done = [0, 0]

        def records() -> Iterator[bytes]:
            for batch in batches:
                for row in zip(*[c.to_pylist() for c in batch.columns]):
                    whole = record(*row)
                    done[0] += len(whole)
                    done[1] += 1
                    yield whole

        fs.create_dir(root, recursive=True)
        write_whole(fs, f"{root}/{name}", records())
        yield pa.RecordBatch.from_pydict({"path": [f"{folder}/{name}"], "bytes": [done[0]], "records": [done[1]]})

    return with_first(pages, least_bytes).mapInArrow(run, MANIFEST)


FIELD = re.compile(rb"^([A-Za-z][A-Za-z0-9-]*): ?([^\r\n]*)\r\n", re.MULTILINE)


def parse_header(data: bytes) -> tuple[dict[str, str], int] | None:
    """The fields of the header that ``data`` begins with, and its length."""
    end = data.find(b"\r\n\r\n")
    if not data.startswith(MAGIC) or end < 0:
        return None
    fields = {k.decode().lower(): v.decode("utf-8", "replace") for k, v in FIELD.findall(data[len(MAGIC) : end + 2])}
    length = fields.get("content-length", "")
    return (fields, end + 4) if length.isdigit() else None


#: Lines that a header may consist of, the last one perhaps not read whole yet.
LINES = re.compile(rb"(?:[A-Za-z][A-Za-z0-9-]*: ?[^\r\n]*+\r\n)*+(?:[A-Za-z][^\r\n]*+)?\r?")


def read_header(file, place: int) -> tuple[dict[str, str], int] | None:
    """``parse_header`` at a place of a file, read in doubling steps to the blank line, however far.

    Reading ends early at a line that isn't a field's, as after magic in a payload.
    """
    file.seek(place)
    head = b""
    while True:
        more = file.read(max(HEADER_BYTES, len(head)))
        head += more
        if not more or b"\r\n\r\n" in head or not (head.startswith(MAGIC) and LINES.fullmatch(head, len(MAGIC))):
            return parse_header(head)


def candidates(path: str, begin: int, end: int) -> Iterator[tuple[int, int]]:
    """Places in [begin, end) where a record may begin, with their successors."""
    fs, at = opened(path)
    with fs.open_input_file(at) as file:
        size = file.size()
        place, kept = begin, b""
        while place < min(end, size):
            file.seek(place)
            kept = file.read(min(READ_BYTES, end - place) + len(MAGIC) - 1)
            found = kept.find(MAGIC)
            while 0 <= found < end - place:
                told = read_header(file, place + found)
                if told is not None:
                    after = place + found + told[1] + int(told[0]["content-length"]) + 4
                    if after <= size:
                        yield place + found, after
                found = kept.find(MAGIC, found + 1)
            place += min(READ_BYTES, end - place)


STEPS = "path string, at bigint, next bigint"


def steps(splits: DataFrame) -> DataFrame:
    """Per candidate of a split the first place beyond the split that its chain comes to."""

    def run(batches):
        for batch in batches:
            for path, begin, end in zip(*[c.to_pylist() for c in batch.columns]):
                found = list(candidates(path, begin, end))
                beyond: dict[int, int] = {}
                for at, after in reversed(found):
                    if after >= end or after in beyond:
                        beyond[at] = after if after >= end else beyond[after]
                rows = sorted(beyond.items())
                yield pa.RecordBatch.from_pydict(
                    {"path": pa.array([path] * len(rows), pa.string()), "at": pa.array([a for a, _ in rows], pa.int64()), "next": pa.array([b for _, b in rows], pa.int64())}
                )

    return splits.mapInArrow(run, STEPS)


def entries(chain: DataFrame, files: DataFrame, longest: int) -> DataFrame:
    """Places reachable from byte 0 of each file, by pointer jumping in about log2(longest) rounds."""
    reached, jump, span = stored(files.select("path", F.lit(0).cast("bigint").alias("at")), "reached"), chain, 1
    while span <= longest:
        ahead = jump.select("path", "at", "next")
        moved = reached.join(ahead, ["path", "at"]).select("path", F.col("next").alias("at"))
        reached = stored(reached.unionAll(moved).distinct(), "reached")
        span *= 2
        if span <= longest:
            second = ahead.select("path", F.col("at").alias("next"), F.col("next").alias("_far"))
            jump = stored(ahead.join(second, ["path", "next"]).select("path", "at", F.col("_far").alias("next")), "jump")
    return reached


RECORDS = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, url string"


def page_of(told: str | None) -> int | None:
    found = re.fullmatch(r"<urn:page:(-?\d+)>", told or "")
    return int(found[1]) if found else None


def parsed(splits: DataFrame, payload: bool = False) -> DataFrame:
    """The records of each split, read from its true entry on."""
    schema = RECORDS + (", html binary" if payload else "")

    def run(batches):
        for batch in batches:
            for path, place, end in zip(*[c.to_pylist() for c in batch.columns]):
                fs, at = opened(path)
                rows, held = [], 0
                with fs.open_input_file(at) as file:
                    size = file.size()
                    while place < min(end, size):
                        told = read_header(file, place)
                        if told is None:
                            raise ValueError(f"{path}: no record at byte {place}")
                        fields, length = told
                        body = int(fields["content-length"])
                        file.seek(place + length)
                        block = file.read(body)
                        digest = fields.get("warc-payload-digest", "").removeprefix("sha1:")
                        if fields["warc-type"] == "response" and base64.b32encode(hashlib.sha1(block).digest()).decode() != digest:
                            raise ValueError(f"{path}: the payload at byte {place} doesn't match its digest")
                        rows.append({
                            "page_id": page_of(fields.get("warc-record-id")), "payload_bytes": int(fields["x-payload-bytes"]),
                            "payload_digest": digest, "record_type": fields["warc-type"],
                            "refers_to": page_of(fields.get("warc-refers-to")), "url": fields.get("warc-target-uri"),
                        } | ({"html": block} if payload else {}))
                        held += len(block) if payload else 0
                        place += length + body + 4
                        if len(rows) >= 4096 or held > 1 << 24:
                            yield to_batch(rows, payload)
                            rows, held = [], 0
                if rows:
                    yield to_batch(rows, payload)

    return splits.mapInArrow(run, schema)


def to_batch(rows: list[dict], payload: bool) -> pa.RecordBatch:
    fields = [("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("url", pa.string())]
    fields += [("html", pa.binary())] if payload else []
    return pa.RecordBatch.from_arrays([pa.array([r[n] for r in rows], k) for n, k in fields], schema=pa.schema(fields))


def read_warc(spark: SparkSession, files: list[tuple[str, int]], *, split_bytes: int = SPLIT_BYTES, payload: bool = False) -> DataFrame:
    """All records of the files, given with their sizes (a row a file on the driver)."""
    listed = spark.createDataFrame([(p, n) for p, n in files if n], "path string, bytes bigint")
    begins = F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("bytes") - 1, F.lit(split_bytes).cast("bigint")))
    splits = listed.select("path", begins.alias("begin")).withColumn("end", F.col("begin") + split_bytes)
    n_splits = sum(-(-n // split_bytes) for _, n in files)
    if not n_splits:
        return parsed(splits, payload)
    longest = max(-(-n // split_bytes) for _, n in files)
    dealt = splits.repartition(n_splits, "path", "begin")
    chain = stored(steps(dealt), "steps")
    true = entries(chain, listed, longest)
    own = F.col("at") - F.col("at") % split_bytes
    todo = true.join(listed, "path").filter(F.col("at") < F.col("bytes")).select("path", "at", (own + split_bytes).alias("end"))
    return parsed(todo.repartition(n_splits, "path", "at"), payload)


def archive(pages: DataFrame, *, folder: str | None = None, least_bytes: int = 0) -> DataFrame:
    """Writes the pages and reads the archives back."""
    spark = pages.sparkSession
    where = folder or scratch(spark, "warc")
    made = stored(write_warc(pages, where, least_bytes=least_bytes), "manifest")
    return read_warc(spark, [(r["path"], r["bytes"]) for r in made.collect()])
