"""N-gram Jaccard join with a count-vector R-tree.

A document's set holds its distinct word shingles.  The join goes by stages:

1. documents with equal sets are one class, represented by its least id;
2. sorted by one global order, with shingles that a sample finds frequent last,
   two sets of the wanted similarity share a shingle of their prefixes; classes
   that share one meet in a group, a large group in cuts of bounded size;
3. in a cut, shingles are hashed into groups and the counts of the groups index
   the sets in an R-tree.  The sum of coordinate minima bounds the overlap of a
   set with a set, or with all sets under a node; sizes and the places of the
   shared shingle bound it as well.  What survives is a candidate pair;
4. candidate pairs, each once, are verified on the shingles of both sides, and
   verified links alone form components.

A set doesn't ask for all its candidates at once.  In a first turn it takes the
few of the highest bounds; in later turns, whose windows grow by a factor, only
those that no chain of links has brought into its component.  So a family of
near copies costs about its size, not the square of it, while a pair that is in
no window is in one component already: no link between components is lost.  In
a group of several cuts, sets outside the group's largest component then also
ask in the other cuts.

The sample only orders shingles; any order gives the same links.

Defined cases.  A null or empty text has an empty set and links with nothing.  A
text with fewer words than a shingle has all its words as one.  Rows that repeat
an id are one document, which links by any of its texts if they differ; ids are
judged, so rows that repeat an id stay or go together.  A null id is kept as a
document that links with nothing.  Only the columns named are read, so extra
columns of any name are harmless.  Hot shingles come last in the order, hot
classes collapse to one representative, and hot groups are cut.
"""

from __future__ import annotations

from itertools import islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, column, dropped, free_name, in_pieces, releasing, stored, text_bytes
from .components import components

#: Documents that the order of shingles is taken from, and shingles it sets last at most.
SAMPLE_DOCS = 8_000
SAMPLE_FREQUENT = 200_000
#: Sets in one cut of a group, about.
CUT_SETS = 1_024
#: Rows that ask in a cut at once.
ASKING_ROWS = 16_384
#: Candidates of a set in the first turn, and by how much the windows grow.
FIRST_WINDOW, GROWTH = 2, 8
#: Groups of rows that are compared as one array, without a tree.
FLAT_ROWS = 16
#: Pairs up to which the ids of their sides are broadcast, 16 bytes a pair.
BROADCAST_PAIRS = 100_000
#: Coordinates of the index; the finest vector has MOST_GROUPS, the others so many that few shingles are in one.
GROUPS, MOST_GROUPS, PER_GROUP = 32, 256, 12
LEAF = 16

MIX = np.uint64(0x9E3779B97F4A7C15)


def shingles(raw: bytes, k: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the k-word shingles of a text in small ASCII letters."""
    words = raw.translate(LOWER).split()
    if len(words) > k:
        grams = map(b" ".join, zip(*[islice(words, j, None) for j in range(k)]))
        found = np.fromiter(map(xxhash.xxh3_64_intdigest, grams), np.uint64, len(words) - k + 1)
        return np.unique(found)
    if words:
        return np.array([xxhash.xxh3_64_intdigest(b" ".join(words))], np.uint64)
    return np.empty(0, np.uint64)


def least_overlap(a: int | np.ndarray, b: int | np.ndarray, percent: int):
    """Overlap that sets of these sizes need: 100 o >= percent (a + b - o)."""
    return -(-(percent * (a + b)) // (100 + percent))


def prefix(found: np.ndarray, frequent: np.ndarray, percent: int) -> np.ndarray:
    """The first shingles in the global order, as many as a linked set can't all miss."""
    n = len(found)
    most = n - -(-percent * n // 100) + 1
    if not n:
        return found
    if len(frequent):
        at = np.minimum(np.searchsorted(frequent, found), len(frequent) - 1)
        late = frequent[at] == found
        found = np.concatenate([found[~late], found[late]])
    return found[:most]


def sample_frequent(docs: DataFrame, k: int) -> np.ndarray:
    """Shingles that two or more sampled documents have, sorted; bounded in number.

    The sample is a fixed number of documents, so its share falls with the corpus.
    Only the order of work depends on it, never a link.
    """
    total = docs.count()
    share = min(1.0, SAMPLE_DOCS / max(1, total))
    some = docs.filter(F.pmod(F.xxhash64(F.lit("order"), "id"), F.lit(1_000_000)) < int(1_000_000 * share) + 1)

    def run(batches):
        for batch in batches:
            found = [shingles(raw, k) for raw in batch.column(0).to_pylist()]
            flat = np.concatenate(found) if found else np.empty(0, np.uint64)
            yield pa.RecordBatch.from_arrays([pa.array(flat.view(np.int64))], ["h"])

    counted = some.select("raw").mapInArrow(releasing(run), "h bigint").groupBy("h").count().filter("count > 1")
    rows = counted.orderBy(F.desc("count"), "h").limit(SAMPLE_FREQUENT).toPandas()
    return np.sort(rows["h"].to_numpy(np.int64).view(np.uint64))


SKETCH = "id bigint, n_shingles bigint, sig_a bigint, sig_b bigint, counts binary, keys array<bigint>"


def sketch(docs: DataFrame, k: int, percent: int, frequent: np.ndarray) -> DataFrame:
    """Per document the size of its set, a 128-bit signature, the count vector and the prefix.

    A set that only an equal one can link with has neither vector nor prefix.
    """
    shared = docs.sparkSession.sparkContext.broadcast(frequent)

    def run(batches):
        order = shared.value
        for batch in batches:
            ids, raws = batch.column(0), batch.column(1).to_pylist()
            sets = [shingles(raw, k) for raw in raws]
            sigs = [xxhash.xxh3_128_intdigest(s.tobytes()) for s in sets]
            alone = [100 * len(s) < percent * (len(s) + 1) for s in sets]
            keys = [s[:0] if a else prefix(s, order, percent) for s, a in zip(sets, alone)]
            vectors = [b"" if a else packed_counts(s) for s, a in zip(sets, alone)]
            ends = np.cumsum([0, *map(len, keys)]).astype(np.int32)
            flat = np.concatenate(keys).view(np.int64) if keys else np.empty(0, np.int64)
            signed = np.array([(s >> 64, s & (1 << 64) - 1) for s in sigs], np.uint64).reshape(-1, 2).view(np.int64)
            yield pa.RecordBatch.from_arrays(
                [ids, pa.array([len(s) for s in sets], pa.int64()), pa.array(signed[:, 0]), pa.array(signed[:, 1]),
                 pa.array(vectors, pa.binary()), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))],
                ["id", "n_shingles", "sig_a", "sig_b", "counts", "keys"],
            )

    return docs.select("id", "raw").mapInArrow(releasing(run), SKETCH)


def count_vector(found: np.ndarray, groups: int = GROUPS) -> np.ndarray:
    return np.bincount(((found * MIX) >> np.uint64(65 - groups.bit_length())).astype(int), minlength=groups).astype(np.int32)


def packed_counts(found: np.ndarray) -> bytes:
    """The count vector in 16-bit integers, rounded up by a scale that the size gives."""
    groups = GROUPS
    while groups < MOST_GROUPS and len(found) > PER_GROUP * groups:
        groups *= 2
    scale = (len(found) >> 16) + 1
    return (-(-count_vector(found, groups) // scale)).astype("<u2").tobytes()


def unpacked_counts(packed: bytes, size: int) -> np.ndarray:
    """Counts that are never below the set's own."""
    return np.frombuffer(packed, "<u2").astype(np.int32) * ((size >> 16) + 1)


def folded(vector: np.ndarray, groups: int = GROUPS) -> np.ndarray:
    """The same counts over fewer groups: neighbours together."""
    return vector.reshape(groups, -1).sum(1) if len(vector) > groups else vector


class CountTree:
    """An R-tree over count vectors; a node keeps the upper corner and the sizes below it.

    Bulk-loaded by halving at the median of the widest coordinate.
    """

    def __init__(self, vectors: np.ndarray, sizes: np.ndarray):
        self.vectors, self.sizes = vectors, sizes
        self.corner, self.least, self.most, self.below = [], [], [], []
        self.root = self._build(np.arange(len(sizes))) if len(sizes) else None

    def _build(self, rows: np.ndarray) -> int:
        node = len(self.corner)
        self.corner.append(self.vectors[rows].max(0))
        self.least.append(self.sizes[rows].min())
        self.most.append(self.sizes[rows].max())
        self.below.append(rows)
        if len(rows) > LEAF:
            part = self.vectors[rows]
            spread = part.max(0).astype(int) - part.min(0)
            by = self.sizes[rows] if self.most[node] - self.least[node] > spread.max() else part[:, spread.argmax()]
            order = np.argsort(by, kind="stable")
            half = len(rows) // 2
            self.below[node] = (self._build(rows[order[:half]]), self._build(rows[order[half:]]))
        return node

    def candidates(self, vector: np.ndarray, size: int, percent: int) -> np.ndarray:
        """Indexed sets whose bound reaches the overlap needed, the closest first."""
        if self.root is None:
            return np.empty(0, int)
        todo, found = [self.root], []
        while todo:
            node = todo.pop()
            low, high = self.least[node], self.most[node]
            if 100 * min(size, high) < percent * max(size, low):
                continue
            need = least_overlap(size, max(low, -(-percent * size // 100)), percent)
            if np.minimum(self.corner[node], vector).sum() < need:
                continue
            if isinstance(self.below[node], tuple):
                todo += self.below[node]
            else:
                found.append(self.below[node])
        if not found:
            return np.empty(0, int)
        rows = np.concatenate(found)
        bound = np.minimum(self.vectors[rows], vector).sum(1)
        good = bound >= least_overlap(size, self.sizes[rows], percent)
        rows, bound = rows[good], bound[good]
        return rows[np.argsort(-bound, kind="stable")]


def linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    both = np.concatenate([a, b])
    both.sort()
    overlap = int((both[1:] == both[:-1]).sum())
    return 100 * overlap >= percent * (len(both) - overlap)


class Rows:
    """Members of groups as columns, sorted by group, cut, home rows first, id."""

    NAMES = ("h", "cut", "home", "id", "n", "pos", "turn", "label")

    def __init__(self, columns: dict[str, np.ndarray], packed: list[bytes]):
        self.columns, self.packed = columns, packed

    @classmethod
    def of(cls, batch: pa.RecordBatch) -> "Rows":
        columns = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in cls.NAMES}
        return cls({c: v if c == "home" else v.astype(np.int64) for c, v in columns.items()}, batch.column("counts").to_pylist())

    def __len__(self) -> int:
        return len(self.packed)

    def __getitem__(self, part: slice) -> "Rows":
        return Rows({k: v[part] for k, v in self.columns.items()}, self.packed[part])

    def __add__(self, other: "Rows") -> "Rows":
        return Rows({k: np.concatenate([v, other.columns[k]]) for k, v in self.columns.items()}, self.packed + other.packed)

    def starts(self) -> np.ndarray:
        """Where the groups' cuts begin."""
        h, cut = self.columns["h"], self.columns["cut"]
        return np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (cut[1:] != cut[:-1])))


def window(turn: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """From which rank of its candidates on a set takes them in a turn, and up to which one.

    In a cut of its own a set has asked in all turns before; in others it may be new.
    """
    high = FIRST_WINDOW * GROWTH ** np.clip(turn, 0, 10)
    return np.where(home & (turn > 0), high // GROWTH, 0), high


def bounded(rows: Rows, vectors: np.ndarray, a: np.ndarray, b: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Which pairs of rows may link, by sizes, places and counts, and their bounds."""
    n, pos, packed = rows.columns["n"], rows.columns["pos"], rows.packed
    na, nb = n[a], n[b]
    need = least_overlap(na, nb, percent)
    good = np.flatnonzero(np.minimum(na - pos[a], nb - pos[b]) >= need)
    bound = np.zeros(len(a), np.int64)
    bound[good] = np.minimum(vectors[a[good]], vectors[b[good]]).sum(1)
    good = good[bound[good] >= need[good]]
    for at in good.tolist():
        x, y = packed[a[at]], packed[b[at]]
        groups = min(len(x), len(y)) // 2
        if groups > GROUPS:
            x, y = (folded(unpacked_counts(p, int(m)), groups) for p, m in ((x, na[at]), (y, nb[at])))
            bound[at] = np.minimum(x, y).sum()
    return good[bound[good] >= need[good]], bound


def taken(rows: Rows, asking: np.ndarray, hit: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of candidates (asking row, hit row): the pairs of ids in the windows, and the groups with candidates behind them."""
    ids, label, turn = (rows.columns[c] for c in ("id", "label", "turn"))
    order = np.lexsort((ids[hit], -bound, asking))
    asking, hit = asking[order], hit[order]
    first = np.flatnonzero(np.append(True, asking[1:] != asking[:-1])) if len(asking) else np.empty(0, int)
    rank = np.arange(len(asking)) - np.repeat(first, np.diff(np.append(first, len(asking))))
    low, high = window(turn[asking], rows.columns["home"][asking])
    apart = label[asking] != label[hit]
    now = apart & (rank >= low) & (rank < high)
    return ids[asking[now]], ids[hit[now]], rows.columns["h"][asking[apart & (rank >= high)]]


def flat_groups(rows: Rows, vectors: np.ndarray, starts: np.ndarray, ends: np.ndarray, percent: int) -> tuple:
    """All groups of few rows at once: each is a single leaf."""
    one, two = [], []
    sizes = ends - starts
    for size in np.unique(sizes).tolist():
        i, j = np.triu_indices(size, 1)
        base = starts[sizes == size][:, None]
        one.append((base + i).ravel())
        two.append((base + j).ravel())
    a, b = (np.concatenate(x) if x else np.empty(0, int) for x in (one, two))
    home, turn = rows.columns["home"], rows.columns["turn"]
    a, b = a[home[a]], b[home[a]]
    good, bound = bounded(rows, vectors, a, b, percent)
    a, b, bound = a[good], b[good], bound[good]
    asking, hit, bound = np.append(a, b), np.append(b, a), np.append(bound, bound)
    asks = home[hit] & (turn[asking] >= 0)
    return taken(rows, asking[asks], hit[asks], bound[asks])


def large_group(rows: Rows, vectors: np.ndarray, start: int, end: int, percent: int) -> tuple:
    """A group's cut: its home rows are indexed, all its rows ask."""
    n, home, turn = rows.columns["n"], rows.columns["home"], rows.columns["turn"]
    inside = np.arange(start, end)
    indexed = inside[home[start:end]]
    tree = CountTree(vectors[indexed], n[indexed])
    asking, hit, bound = [], [], []
    for q in inside[turn[start:end] >= 0].tolist():
        found = indexed[tree.candidates(vectors[q], int(n[q]), percent)]
        found = found[found != q]
        good, b = bounded(rows, vectors, np.full(len(found), q), found, percent)
        asking.append(np.full(len(good), q))
        hit.append(found[good])
        bound.append(b[good])
    if not asking:
        return taken(rows, *[np.empty(0, int)] * 3)
    return taken(rows, np.concatenate(asking), np.concatenate(hit), np.concatenate(bound))


def group_candidates(rows: Rows, percent: int) -> pa.RecordBatch:
    """Candidate pairs (a < b) of whole groups, and rows with the group alone where more are to come."""
    found = [(np.empty(0, np.int64),) * 3]
    if len(rows):
        n = rows.columns["n"].tolist()
        vectors = np.stack([folded(unpacked_counts(p, m)) for p, m in zip(rows.packed, n)])
        starts = rows.starts()
        ends = np.append(starts[1:], len(rows))
        few = ends - starts <= FLAT_ROWS
        found.append(flat_groups(rows, vectors, starts[few], ends[few], percent))
        found += [large_group(rows, vectors, s, e, percent) for s, e in zip(starts[~few].tolist(), ends[~few].tolist())]
    x, y, more = (np.concatenate(c) for c in zip(*found))
    pairs = np.unique(np.stack([np.minimum(x, y), np.maximum(x, y)], 1), axis=0)
    more = np.unique(more)
    ids = [pa.concat_arrays([pa.array(pairs[:, c], pa.int64()), pa.nulls(len(more), pa.int64())]) for c in (0, 1)]
    return pa.RecordBatch.from_arrays([*ids, pa.concat_arrays([pa.nulls(len(pairs), pa.int64()), pa.array(more, pa.int64())])], ["a", "b", "h"])


def candidates(dealt: DataFrame, percent: int) -> DataFrame:
    """(a, b, null) for candidate pairs and (null, null, h) for groups to be asked again.

    A task streams its groups; it holds a batch and one group's cut.
    """

    def run(batches):
        held = None
        for batch in batches:
            rows = Rows.of(batch) if held is None else held + Rows.of(batch)
            last = int(rows.starts()[-1]) if len(rows) else 0
            if last:
                yield group_candidates(rows[:last], percent)
            held = rows[last:]
            n_home = int(held.columns["home"].sum())
            if len(held) - n_home > ASKING_ROWS:  # its home rows are whole
                yield group_candidates(held, percent)
                held = held[:n_home]
                held.columns["turn"] = np.full(n_home, -1)
        if held is not None:
            yield group_candidates(held, percent)

    names = [*Rows.NAMES, "counts"]
    sorted_rows = dealt.repartition("h", "cut").sortWithinPartitions("h", "cut", F.desc("home"), "id")
    return sorted_rows.select(*names).mapInArrow(releasing(run), "a bigint, b bigint, h bigint")


def asked_again(members: DataFrame, labels: DataFrame, again: DataFrame, turn: int) -> DataFrame:
    """The rows of a later turn: members of groups with more to ask, under the components found so far."""
    known = labels.select("id", F.col("component").alias("label"))
    left = members.join(again, "h", "left_semi").join(known, "id", "left").withColumn("label", F.coalesce("label", "id"))
    home = left.withColumns({"home": F.lit(True), "turn": F.lit(turn)})
    cut = left.filter("n_cuts > 1")
    main = cut.groupBy("h", "label").count().groupBy("h").agg(F.max_by("label", F.struct("count", "label")).alias("main"))
    foreign = (
        cut.join(main, "h").filter("label <> main").drop("main")
        .withColumns({"home": F.lit(False), "turn": F.lit(turn - 1), "other": F.explode(F.sequence(F.lit(0), F.col("n_cuts") - 1))})
        .filter("other <> cut").withColumn("cut", F.col("other")).drop("other")
    )
    return home.unionByName(foreign)


def shingle_sets(source: DataFrame, k: int) -> DataFrame:
    """id and its sorted distinct shingle hashes."""

    def run(batches):
        for batch in batches:
            ids, raws = batch.column(0), batch.column(1).to_pylist()
            done = 0
            for part in in_pieces(raws, len, 1 << 22):
                sets = [shingles(raw, k) for raw in part]
                ends = np.cumsum([0, *map(len, sets)]).astype(np.int32)
                flat = pa.array(np.concatenate(sets).view(np.int64))
                yield pa.RecordBatch.from_arrays([ids.slice(done, len(part)), pa.ListArray.from_arrays(pa.array(ends), flat)], ["id", "found"])
                done += len(part)

    return source.select("id", "raw").mapInArrow(releasing(run), "id bigint, found array<bigint>")


def verified(pairs: DataFrame, source: DataFrame, k: int, percent: int) -> DataFrame:
    """A table of the pairs that link, by the shingles of both sides; each side's are made once."""
    ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    few = pairs.count() <= BROADCAST_PAIRS
    sets = stored(shingle_sets(source.join(F.broadcast(ids) if few else ids.hint("shuffle_hash"), "id"), k), "sets")
    both = pairs.join(sets.select(F.col("id").alias("a"), F.col("found").alias("found_a")), "a").join(
        sets.select(F.col("id").alias("b"), F.col("found").alias("found_b")), "b"
    )
    overlap = F.size(F.array_intersect("found_a", "found_b")).cast("bigint")
    out = stored(both.filter(100 * overlap >= percent * (F.size("found_a") + F.size("found_b") - overlap)).select("a", "b"), "links")
    dropped(sets)
    return out


def jaccard_components(docs: DataFrame, k: int = 5, percent: int = 80, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per row of ``docs``: doc_id, n_shingles, component_id and representative of its class of equal sets.

    Two documents link when 100 x intersection >= percent x union.
    """
    if not 50 <= percent <= 100:
        raise ValueError("percent must be from 50 to 100")
    source = docs.select(column(doc_id).cast("bigint").alias("id"), text_bytes(text).alias("raw"))
    frequent = sample_frequent(source, k)
    sketched = stored(sketch(source, k, percent, frequent), "sketches")
    linkable = sketched.filter("id is not null and n_shingles > 0")
    classes = stored(
        linkable.groupBy("sig_a", "sig_b").agg(
            F.min("id").alias("rep"), F.first("n_shingles").cast("int").alias("n"), F.first("counts").alias("counts"), F.first("keys").alias("keys")
        ),
        "classes",
    )
    places = classes.select(F.col("rep").alias("id"), F.posexplode("keys").alias("pos", "h"))
    met = places.groupBy("h").agg(F.ceil(F.count("*") / CUT_SETS).cast("int").alias("n_cuts"), F.count("*").alias("n_rows")).filter("n_rows > 1").drop("n_rows")
    cut = F.pmod(F.xxhash64("id"), "n_cuts").cast("int").alias("cut")
    vectors = classes.filter("n > 0 and size(keys) > 0").select(F.col("rep").alias("id"), "n", "counts")
    members = stored(places.join(met, "h").select("h", "n_cuts", cut, "id", "pos").join(vectors, "id"), "members")

    rows = members.withColumns({"home": F.lit(True), "turn": F.lit(0), "label": F.col("id")})
    links, tried, found, turn = None, None, None, 0
    while True:
        told = stored(candidates(rows, percent), "candidates")
        pairs = told.filter("h is null").select("a", "b").distinct()
        fresh = stored(pairs if tried is None else pairs.join(tried, ["a", "b"], "left_anti"), "pairs")
        new = verified(fresh, source, k, percent)
        links, tried = (new, fresh) if turn == 0 else (links.unionAll(new), tried.unionAll(fresh))
        again = told.filter("h is not null").select("h")
        if turn == 0:
            again = again.unionAll(members.filter("n_cuts > 1").select("h"))
        again = stored(again.distinct(), "again")
        dropped(told)
        found = components(links)
        if again.isEmpty():
            break
        turn += 1
        rows = asked_again(members, found, again, turn)

    moved = classes.select("sig_a", "sig_b", "rep").join(found, classes["rep"] == found["id"], "left").select(
        "sig_a", "sig_b", "rep", F.coalesce("component", "rep").alias("component")
    )
    full = sketched.select("id", "n_shingles", "sig_a", "sig_b").join(moved, ["sig_a", "sig_b"], "left")
    alone = F.col("id").isNull() | (F.col("n_shingles") == 0)
    return full.select(
        F.col("id").alias("doc_id"), "n_shingles",
        F.when(alone, F.col("id")).otherwise(F.col("component")).alias("component_id"),
        F.when(alone, F.col("id")).otherwise(F.col("rep")).alias("representative"),
    )


def one_of_each(docs: DataFrame, k: int = 5, percent: int = 80, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with one document of each group left: that of the least id."""
    found = jaccard_components(docs, k, percent, doc_id=doc_id, text=text)
    gone = found.filter("doc_id <> component_id").select(F.col("doc_id").alias(free_name(docs, "gone"))).distinct()
    return docs.join(gone, column(doc_id) == gone[gone.columns[0]], "left_anti")
