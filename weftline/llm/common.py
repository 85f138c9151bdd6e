"""What the training-data operators share: folders, byte-level words, Arrow batches."""

from __future__ import annotations

import atexit
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from itertools import islice

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII capitals to small letters; every other byte stays.
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))

#: ASCII capitals to small letters, other ASCII but letters and digits to blanks.
#: Bytes from 128 on belong to characters beyond ASCII, which are word characters.
LOWER_ALNUM = bytes(
    LOWER[b] if b >= 128 or chr(b).isalnum() else 32 for b in range(256)
)

ASCII_CAPITALS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
ASCII_SMALL = "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as a URI or a path.

    The session's ``spark.checkpoint.dir`` names it.  Where that is unset, a
    session on one machine gets a temporary folder, another the warehouse.
    """
    told = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not told:
        alone = spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")
        told = tempfile.mkdtemp(prefix="weftline-") if alone else f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/weftline-shared"
        spark.sparkContext.setCheckpointDir(told)
    return told.rstrip("/")


def scratch(spark: SparkSession, what: str) -> str:
    """A fresh path in the shared folder, deleted when the driver ends."""
    path = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    atexit.register(_forget, spark, path)
    return path


def _forget(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session ended first: its folder goes with the cluster
        pass


def stored(df: DataFrame, what: str) -> DataFrame:
    """``df`` as a table in the shared folder: lineage ends and lost executors cost nothing."""
    path = scratch(df.sparkSession, what)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def dropped(*tables: DataFrame) -> None:
    """Deletes tables made by ``stored`` that nothing to come reads."""
    for t in tables:
        _forget(t.sparkSession, t.stored_at)


def column(name: str) -> Column:
    """The column of exactly this name, whatever dots or quotes are in it."""
    return F.col("`" + name.replace("`", "``") + "`")


def free_name(df: DataFrame, like: str) -> str:
    """A name that no column of ``df`` has, in any case of letters."""
    taken = {c.lower() for c in df.columns}
    name = like
    while name.lower() in taken:
        name += "_"
    return name


def text_bytes(name: str = "text"):
    """The column's UTF-8 bytes; null counts as empty."""
    return F.coalesce(column(name), F.lit("")).cast("binary")


#: Bytes of texts that a worker takes out of an Arrow batch at once.
PART_BYTES = 1 << 21


def parts(values: pa.Array, most: int = PART_BYTES) -> Iterator[pa.Array]:
    """Slices of a column of texts or bytes, of about ``most`` bytes each or a single row."""
    ends = pc.cumulative_sum(pc.cast(pc.fill_null(pc.binary_length(values), 0), pa.int64())).to_pylist()
    begin, before = 0, 0
    for at, end in enumerate(ends):
        if end - before >= most:
            yield values.slice(begin, at + 1 - begin)
            begin, before = at + 1, end
    if begin < len(values):
        yield values.slice(begin)


def struct_of(fields: dict[str, tuple[str, pa.DataType]], each: Callable[[list], list], after: Callable[[], None] = lambda: None, most: int = PART_BYTES) -> Callable[[Column], Column]:
    """A function of a column of texts or bytes to a struct: ``each`` makes the fields' lists of a list of values.

    Other columns stay in the JVM, a worker holds a part of a batch at a time,
    and at the end of a task it gives back what it took.  The function counts as
    not deterministic, so that the optimizer never runs it twice.
    """

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        try:
            for values in batches:
                made = [
                    pa.StructArray.from_arrays([as_array(c, kind) for c, (_, kind) in zip(each(part.to_pylist()), fields.values())], list(fields))
                    for part in parts(values, most)
                ]
                yield pa.concat_arrays(made) if made else pa.array([], pa.struct([(n, kind) for n, (_, kind) in fields.items()]))
        finally:
            after()
            released()

    return F.arrow_udf(run, "struct<" + ", ".join(f"{n}: {kind}" for n, (kind, _) in fields.items()) + ">").asNondeterministic()


def with_results(docs: DataFrame, made: Column, names: list[str], without: tuple[str, ...] = ()) -> DataFrame:
    """``docs`` with fields of the struct ``made`` as columns; columns of these names are replaced, others stay."""
    result = free_name(docs, "made")
    gone = {n.lower() for n in (*names, *without)}
    own = [column(c) for c in docs.columns if c.lower() not in gone]
    return docs.withColumn(result, made).select(*own, *[column(result)[n].alias(n) for n in names])


def releasing(run: Callable) -> Callable:
    """A function over batches that gives memory back when its task ends."""

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            released()

    return wrapped


def released() -> None:
    """Gives memory that Python and Arrow hold without need back to the system."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library: it keeps its memory
        pass


def as_array(values, kind: pa.DataType) -> pa.Array:
    if isinstance(values, pa.Array) and values.type == kind:
        return values
    if isinstance(values, pa.Array):
        return values.cast(kind)
    return pa.array(values, kind)


def in_pieces(values: list, weight: Callable, most: int) -> Iterator[list]:
    """Consecutive runs of ``values`` whose weights sum to about ``most``."""
    part, heavy = [], 0
    for v in values:
        part.append(v)
        heavy += weight(v)
        if heavy >= most:
            yield part
            part, heavy = [], 0
    if part:
        yield part


class Recent:
    """A cache in two generations: at most twice ``bound`` entries stay in memory."""

    def __init__(self, bound: int):
        self.bound, self.new, self.old = bound, {}, {}

    def known(self, keys) -> tuple[dict, list]:
        """What the cache has of the distinct ``keys``, and the keys it lacks."""
        new, old, found, lacking = self.new.get, self.old.get, {}, []
        for k in keys:
            v = new(k)
            if v is None:
                v = old(k)
            if v is None:
                lacking.append(k)
            else:
                found[k] = v
        return found, lacking

    def whole(self, keys: set, make: Callable[[list], dict]) -> dict:
        """A dict with all the distinct ``keys``; ``make`` gives entries for those the cache lacks.

        Until the next call it may outgrow the bound by the keys of this one.
        """
        if len(self.new) > self.bound:
            self.old, self.new = self.new, {}
        lacking = keys.difference(self.new)
        if lacking:
            back = {k: self.old[k] for k in lacking if k in self.old}
            self.new.update(back)
            lacking.difference_update(back)
            self.new.update(make(list(lacking)))
        return self.new

    def rest(self, most: int = 30_000) -> None:
        """Forgets all but the entries that came first, mostly those of frequent keys."""
        self.old, self.new = {}, dict(islice(self.new.items(), most))

    def keep(self, entries: dict) -> None:
        """Adds entries; those found long ago go first."""
        if len(self.new) + len(entries) > self.bound:
            self.old, self.new = self.new, {}
        self.new.update(islice(entries.items(), self.bound))


@contextmanager
def few_collections():
    """No cyclic collections inside: caches hold no cycles, and scanning them is slow."""
    on = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if on:
            gc.enable()
