"""Models from sufficient statistics, boosted trees from histograms, and their measures."""

from __future__ import annotations

import heapq
import threading
from collections.abc import Callable, Iterator
from concurrent.futures import Future

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .encoders import FLAG, packed_form
from .merge import merged, summed
from .order import auc  # noqa: F401  a measure like the others here

#: Columns up to which moments are aggregate expressions rather than Arrow partial sums.
EXPRESSION_COLUMNS = 8
MOST_COLUMNS = 1_000


def moments(df: DataFrame, features: list[str], target: str, by: str | None = None, kernel: str | None = None) -> dict:
    """Sums of products of (1, features, target), per value of ``by``: one pass for any grid.

    ``kernel`` is expressions, blocks or rows; by default expressions for few
    columns.  Products are of differences to a pivot, a row's values, so that they
    don't cancel at large numbers of rows; sums of the columns themselves follow.
    """
    columns = [*features, target]
    if len(columns) + 1 > MOST_COLUMNS:
        raise MemoryError(f"{len(columns) + 1} columns make too large a matrix of moments")
    group = F.coalesce(F.col(by), F.lit(-1)).cast("int") if by else F.lit(0)
    wide = df.select(group.alias("_by"), *[F.col(f"`{c}`").cast("double").alias(f"x{k}") for k, c in enumerate(columns)])
    first = wide.drop("_by").na.drop().first()
    pivot = np.array(first if first is not None else [0.0] * len(columns), float)
    kernel = kernel or ("expressions" if len(columns) + 1 <= EXPRESSION_COLUMNS else "blocks")
    if kernel == "blocks" and packed_form(df):
        thin, bits = numbered(df, columns, [group.alias("_by")])
        found = moments_by_blocks(thin, pivot, bits)
    else:
        found = {"expressions": moments_by_expressions, "blocks": moments_by_blocks, "rows": moments_by_rows}[kernel](wide, pivot)
    return {b: Moments.about(m, pivot) for b, m in found.items()}


class Moments(np.ndarray):
    """Sums of products of z, which also keep the sums about a pivot that they come from.

    Sums and differences of moments about one pivot keep it, so that centring
    never subtracts large squares.
    """

    shifted: np.ndarray | None
    pivot: np.ndarray | None

    @classmethod
    def about(cls, shifted: np.ndarray, pivot: np.ndarray) -> "Moments":
        shift = np.eye(len(shifted))
        shift[1:, 0] = pivot
        out = (shift @ shifted @ shift.T).view(cls)
        out.shifted, out.pivot = shifted, pivot
        return out

    def __array_finalize__(self, other: object) -> None:
        self.shifted = self.pivot = None

    def _with(self, other: object, sign: int):
        if isinstance(other, Moments) and other.pivot is not None and self.pivot is not None and np.array_equal(other.pivot, self.pivot):
            return Moments.about(self.shifted + sign * other.shifted, self.pivot)
        plain = np.asarray(other)
        return self if not plain.any() else np.asarray(self) + sign * plain

    def __add__(self, other: object):
        return self._with(other, 1)

    __radd__ = __add__

    def __sub__(self, other: object):
        return self._with(other, -1)


def moments_by_expressions(wide: DataFrame, pivot: np.ndarray) -> dict:
    """One aggregate of products, inside generated code."""
    z = [F.lit(1.0), *[F.col(c) - F.lit(float(v)) for c, v in zip(wide.columns[1:], pivot)]]
    pairs = [(i, j) for i in range(len(z)) for j in range(i, len(z))]
    out = {}
    for r in wide.groupBy("_by").agg(*[F.sum(z[i] * z[j]).alias(f"m{i}_{j}") for i, j in pairs]).collect():
        m = np.zeros((len(z), len(z)))
        for i, j in pairs:
            m[i, j] = m[j, i] = r[f"m{i}_{j}"] or 0.0
        out[r["_by"]] = m
    return out


def numbered(df: DataFrame, columns: list[str], keep: list[Column]) -> tuple[DataFrame, dict[int, tuple[str, int]]]:
    """``keep`` and the columns as doubles x0, x1, ...; flags that are bits stay so, with (number's column, bit) by place."""
    frame, place = packed_form(df) or (df, {})
    bits = {k: place[c] for k, c in enumerate(columns) if c in place}
    plain = [F.col(f"`{c}`").cast("double").alias(f"x{k}") for k, c in enumerate(columns) if k not in bits]
    return frame.select(*keep, *plain, *[F.col(to) for to in sorted({to for to, _ in bits.values()})]), bits


def numbers_of(batch: pa.RecordBatch, k: int, bits: dict[int, tuple[str, int]]) -> pa.Array:
    if k not in bits:
        return batch.column(f"x{k}")
    to, bit = bits[k]
    return pa.array(((batch.column(to).to_numpy(zero_copy_only=False) >> bit) & 1).astype(float))


def moments_by_blocks(wide: DataFrame, pivot: np.ndarray, bits: dict[int, tuple[str, int]] | None = None) -> dict:
    """Products of whole Arrow batches, merged in parallel; ``bits`` as ``numbered`` tells them."""
    names, bits = range(len(pivot)), bits or {}

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            of = batch.column(0).to_numpy(zero_copy_only=False)
            x = np.ones((len(names) + 1, batch.num_rows))
            for k, v in enumerate(pivot, 1):
                np.subtract(numbers_of(batch, k - 1, bits).to_numpy(zero_copy_only=False), v, out=x[k])
            groups = np.unique(of)
            for b in groups:
                mine = x[:, of == b] if len(groups) > 1 else x
                sums[int(b)] = sums.get(int(b), 0) + mine @ mine.T
        yield pa.RecordBatch.from_pydict({"b": pa.array(list(sums), pa.int32()), "m": pa.array([m.tobytes() for m in sums.values()], pa.binary())})

    return {b: m.reshape(len(names) + 1, -1) for b, m in summed(wide.mapInArrow(partial, "b int, m binary")).items()}


def moments_by_rows(wide: DataFrame, pivot: np.ndarray) -> dict:
    """The interpreted kernel: products in Python over the rows of pandas batches, a column at a time."""
    p = len(wide.columns)

    def partial(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sums: dict[int, np.ndarray] = {}
        for pdf in batches:
            for b, rows in pdf.groupby("_by"):
                z = np.ones((len(rows), p))
                z[:, 1:] = rows.iloc[:, 1:].to_numpy(float) - pivot
                m = sums.setdefault(int(b), np.zeros((p, p)))
                for i in range(p):
                    with np.errstate(invalid="ignore"):  # zero times infinity isn't a number, as in every kernel
                        m[i, i:] += z[:, i] @ z[:, i:]
        for m in sums.values():
            m += np.triu(m, 1).T
        yield pd.DataFrame({"b": list(sums), "m": [m.tobytes() for m in sums.values()]})

    return {b: m.reshape(p, p) for b, m in summed(wide.mapInPandas(partial, "b int, m binary")).items()}


def centred(m: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, float, float]:
    """Centred cross products of features, with the target, means and the number of rows."""
    pivot = getattr(m, "pivot", None)
    own = np.asarray(m if pivot is None else m.shifted)
    n = own[0, 0]
    mean = own[0] / n if n else own[0]
    s = own - n * np.outer(mean, mean)
    at = mean if pivot is None else mean + np.append(0.0, pivot)
    return s[1:-1, 1:-1], s[1:-1, -1], at[1:-1], at[-1], n


def solve_ridge(m: np.ndarray, alpha: float) -> dict:
    sxx, sxy, mx, my, _ = centred(m)
    a = sxx + alpha * np.eye(len(sxx))
    try:
        w = np.linalg.solve(a, sxy)
    except np.linalg.LinAlgError:
        w = np.linalg.pinv(a) @ sxy
    return {"kind": "linear", "w": w.tolist(), "b": float(my - mx @ w)}


def solve_elastic_net(m: np.ndarray, alpha: float, rho: float, rounds: int = 1000, tol: float = 1e-9) -> dict:
    """Cyclic coordinate descent on covariances."""
    sxx, sxy, mx, my, n = centred(m)
    c, b = sxx / n, sxy / n
    w = np.zeros(len(b))
    cw = np.zeros(len(b))
    for _ in range(rounds):
        most = 0.0
        for j in range(len(b)):
            z = b[j] - cw[j] + c[j, j] * w[j]
            new = np.sign(z) * max(abs(z) - alpha * rho, 0.0) / max(c[j, j] + alpha * (1 - rho), 1e-300)
            if new != w[j]:
                cw += c[:, j] * (new - w[j])
                most = max(most, abs(new - w[j]))
                w[j] = new
        if most <= tol * (np.abs(w).max() + 1e-12):
            break
    return {"kind": "linear", "w": w.tolist(), "b": float(my - mx @ w)}


def moment_errors(m: np.ndarray, model: dict) -> tuple[float, float]:
    """Sum of squared errors and rows, from the moments of the rows to score."""
    v, own = np.array([model["b"], *model["w"], -1.0]), np.asarray(m)
    if getattr(m, "pivot", None) is not None:
        own = m.shifted
        v[0] += v[1:] @ m.pivot
    return float(max(v @ own @ v, 0.0)), float(own[0, 0])


def logistic(df: DataFrame, features: list[str], target: str, alpha: float = 1e-3, rounds: int = 15) -> dict:
    """Reweighted least squares: each round is one pass of weighted moments."""
    w = np.zeros(len(features) + 1)
    for _ in range(rounds):
        told = F.lit(float(w[0]))
        for c, k in zip(features, w[1:]):
            told = told + F.col(c) * F.lit(float(k))
        p = F.least(F.greatest(1 / (1 + F.exp(-told)), F.lit(1e-9)), F.lit(1 - 1e-9))
        root = F.sqrt(p * (1 - p))
        weighted = df.select(root.alias("_one"), *[(F.col(c) * root).alias(c) for c in features], ((F.col(target) - p) / root).alias("_g"))
        m = moments(weighted, ["_one", *features], "_g")[0]
        ridge = alpha * np.eye(len(w))
        ridge[0, 0] = 0
        step = np.linalg.lstsq(m[1:-1, 1:-1] + ridge, m[1:-1, -1] - ridge @ w, rcond=None)[0]
        w = w + step
        if np.abs(step).max() < 1e-8:
            break
    return {"kind": "logistic", "w": w[1:].tolist(), "b": float(w[0])}


#: Distinct values of a feature up to which a task counts them.
COUNTED_VALUES = 50_000


def bin_edges(df: DataFrame, features: list[str], bins: int) -> list[list[float]]:
    """Quantiles of each feature, from counts of its values; those of many values take a sketch.

    A column of zeros and ones needs no values, as its counts tell them.
    """
    flags = {f.name for f in df.schema if f.metadata.get(FLAG)}
    shares = [k / bins for k in range(1, bins)]
    told: dict[str, list[float]] = {}
    two = [c for c in features if c in flags]
    if two:
        found = flag_counts(df, two) if packed_form(df) else df.agg(*[F.struct(F.count(f"`{c}`"), F.sum(f"`{c}`")).alias(f"e{i}") for i, c in enumerate(two)]).first()
        told |= {c: [float(e[0] - e[1] < s * e[0]) for s in shares if e[0]] for c, e in zip(two, found)}
    others = [c for c in features if c not in flags]
    counted = value_counts(df, others) if others else {}
    many = [c for c in others if counted[c] is None]
    if many:
        found = df.agg(*[F.percentile_approx(f"`{c}`", shares, 10_000).alias(f"e{i}") for i, c in enumerate(many)]).first()
        told |= {c: e or [] for c, e in zip(many, found)}
    for c in others:
        if counted[c] is not None:
            values, counts = counted[c]
            ends = np.cumsum(counts)
            told[c] = values[np.searchsorted(ends, [s * ends[-1] for s in shares])].tolist() if len(ends) else []
    return [sorted(set(map(float, told[c]))) for c in features]


def flag_counts(df: DataFrame, flags: list[str]) -> list[tuple[float, float]]:
    """(rows, ones) of flags kept as bits."""
    thin, bits = numbered(df, flags, [])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros(len(flags) + 1)
        for batch in batches:
            out += [batch.num_rows, *[np.nansum(numbers_of(batch, k, bits).to_numpy(zero_copy_only=False)) for k in range(len(flags))]]
        yield pa.RecordBatch.from_pydict({"b": pa.array([0], pa.int32()), "m": [out.tobytes()]})

    rows, *ones = summed(thin.mapInArrow(count, "b int, m binary"), size=8.0 * len(flags)).get(0, np.zeros(len(flags) + 1))
    return [(rows, n) for n in ones]


def value_counts(df: DataFrame, columns: list[str]) -> dict[str, tuple[np.ndarray, np.ndarray] | None]:
    """(values in order, rows of each) by column; None for a column of many values."""

    def added(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
        values, at = np.unique(np.concatenate([v for v, _ in parts]), return_inverse=True)
        return values, np.bincount(at, np.concatenate([n for _, n in parts]), len(values)).astype(np.int64)

    def told(sums: dict[int, tuple | None]) -> dict:
        own = {k: v if v is not None and len(v[0]) <= COUNTED_VALUES else None for k, v in sums.items()}
        return {"c": list(own), "v": [None if v is None else v[0].tobytes() for v in own.values()], "n": [None if v is None else v[1].tobytes() for v in own.values()]}

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, tuple | None] = {}
        waiting: dict[int, list[np.ndarray]] = {}

        def settle() -> None:
            for k, arrays in waiting.items():
                if sums.get(k, ()) is not None:
                    new = np.unique(np.concatenate(arrays), return_counts=True)
                    got = added([sums[k], new]) if k in sums else new
                    sums[k] = got if len(got[0]) <= COUNTED_VALUES else None
            waiting.clear()

        rows = 0
        for batch in batches:
            for k in range(len(columns)):
                if sums.get(k, ()) is not None:
                    waiting.setdefault(k, []).append(batch.column(k).drop_null().to_numpy(zero_copy_only=False))
            rows += batch.num_rows
            if rows >= COUNTED_VALUES:
                settle()
                rows = 0
        settle()
        yield pa.RecordBatch.from_pydict(told(sums), schema)

    def fold(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sums: dict[int, tuple | None] = {}
        for pdf in batches:
            for k, v, n in zip(pdf["c"], pdf["v"], pdf["n"]):
                if v is None or sums.get(k, ()) is None:
                    sums[k] = None
                else:
                    new = (np.frombuffer(v), np.frombuffer(n, np.int64))
                    got = added([sums[k], new]) if k in sums else new
                    sums[k] = got if len(got[0]) <= COUNTED_VALUES else None
        yield pd.DataFrame(told(sums))

    schema = pa.schema([("c", pa.int32()), ("v", pa.binary()), ("n", pa.binary())])
    numbers, _ = numbered(df, columns, [])
    parts = merged(numbers.mapInArrow(count, "c int, v binary, n binary"), "c int, v binary, n binary", fold)
    got = next(fold(iter([pd.DataFrame([tuple(r) for r in parts], columns=["c", "v", "n"])])))
    nothing = (np.empty(0), np.empty(0, np.int64))
    out = {columns[k]: None if v is None else (np.frombuffer(v), np.frombuffer(n, np.int64)) for k, v, n in zip(got["c"], got["v"], got["n"])}
    return {c: out.get(c, nothing) for c in columns}


def binned(df: DataFrame, features: list[str], edges: list[list[float]], keep: list) -> DataFrame:
    """Features as bin numbers; 0 holds missing values."""

    def one(c: str, e: list[float]) -> Column:
        above = F.lit(1)
        for x in e:
            above = above + (F.col(c) > x).cast("int")
        return F.coalesce(above, F.lit(0)).cast("tinyint")

    return df.select(*keep, *[one(c, e).alias(f"b{i}") for i, (c, e) in enumerate(zip(features, edges))])


#: Rows that a task of a pass has at least: passes are many and short.
TASK_ROWS = 100_000
#: Further leaves whose best splits are scanned along, as they are likely to come next.
LEAVES_AHEAD = 7
#: Trees after which every row's gradient is brought up to date and kept.
GRADIENT_TREES = 8
#: Leaves of a tree up to which a row's leaf is found by sets of leaves, as bits of a number.
LEAF_BITS = 16
#: Numbers of bins that features packed into one code may have together.
CODES = 4096


class Packing:
    """Features of few bins share a code, a number of mixed radix, so a pass counts codes and not every feature."""

    def __init__(self, sizes: list[int]):
        self.sizes, self.place, self.totals = sizes, [], []
        for n in sizes:
            if not self.totals or self.totals[-1] * n > CODES:
                self.totals.append(1)
            self.place.append((len(self.totals) - 1, self.totals[-1]))
            self.totals[-1] *= n

    def packed(self, bins: list[np.ndarray]) -> np.ndarray:
        out = np.zeros((len(self.totals), len(bins[0])), np.uint16)
        for b, (g, stride) in zip(bins, self.place):
            out[g] += b.astype(np.uint16) * np.uint16(stride)
        return out

    def goes_left(self, codes: np.ndarray, f: int, b: int, missing_left: bool) -> np.ndarray:
        g, stride = self.place[f]
        own = np.arange(self.totals[g]) // stride % self.sizes[f]
        return ((own <= b) & ((own > 0) | missing_left))[codes[g]]

    def leaf_of(self, tree: list[tuple], codes: np.ndarray) -> np.ndarray:
        """The node that each row ends in; children come after their parents."""
        at = np.zeros(codes.shape[1], np.int16)
        for node, (f, b, left, right, _, missing_left) in enumerate(tree):
            if f >= 0:
                at = np.where(at == node, np.where(self.goes_left(codes, f, b, missing_left), np.int16(left), np.int16(right)), at)
        return at

    def finder(self, tree: list[tuple], out: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
        """A function of codes to what ``out`` has for the node that each row ends in.

        Each code names the leaves that its features leave open, and the one left by all codes is the row's.
        """
        leaves = [node for node, n in enumerate(tree) if n[0] < 0]
        if len(leaves) > LEAF_BITS:
            return lambda codes: out[self.leaf_of(tree, codes)]
        below = [0] * len(tree)
        for node in reversed(range(len(tree))):
            f, _, left, right, *_ = tree[node]
            below[node] = 1 << leaves.index(node) if f < 0 else below[left] | below[right]
        every = np.uint32(below[0])
        open_: dict[int, np.ndarray] = {}
        for f, b, left, right, _, missing_left in tree:
            if f >= 0:
                g, stride = self.place[f]
                own = np.arange(self.totals[g]) // stride % self.sizes[f]
                goes = (own <= b) & ((own > 0) | missing_left)
                open_[g] = open_.get(g, every) & np.where(goes, every & ~np.uint32(below[right]), every & ~np.uint32(below[left]))
        told = np.zeros(int(every) + 1, out.dtype)
        told[[1 << k for k in range(len(leaves))]] = out[leaves]

        def find(codes: np.ndarray) -> np.ndarray:
            left = None
            for g, sets in open_.items():
                left = sets[codes[g]] if left is None else np.bitwise_and(left, sets[codes[g]], out=left)
            return told[left] if left is not None else np.full(codes.shape[1], out[leaves[0]])

        return find

    def tree_values(self, tree: list[tuple], codes: np.ndarray) -> np.ndarray:
        """Values by tree; nodes are (feature, bin, left, right, value, missing goes left), feature -1 at leaves."""
        return self.values_of(tree)(codes)

    def values_of(self, tree: list[tuple]) -> Callable[[np.ndarray], np.ndarray]:
        return self.finder(tree, np.array([n[4] for n in tree]))

    def empty(self) -> list[np.ndarray]:
        return [np.zeros((n, 2)) for n in self.totals]

    def count(self, sums: list[np.ndarray], codes: np.ndarray, gradient: np.ndarray) -> None:
        for own, total in zip(codes, sums):
            at = own.astype(np.intp)
            total[:, 0] += np.bincount(at, gradient, len(total))
            total[:, 1] += np.bincount(at, minlength=len(total))

    def by_feature(self, sums: list[np.ndarray], width: int) -> np.ndarray:
        out = np.zeros((len(self.sizes), width, 2))
        for f, (n, (g, stride)) in enumerate(zip(self.sizes, self.place)):
            out[f, :n] = sums[g].reshape(-1, n, stride, 2).sum((0, 2))
        return out


def bins_of(values: pa.Array, edges: list[float]) -> np.ndarray:
    """What ``binned`` gives for one column: edges below the value and 1, or 0 where it is missing."""
    x = values.to_numpy(zero_copy_only=False)
    if len(edges) <= 4:
        out = np.ones(len(x), np.uint8)
        for e in edges:
            out += ~(x <= e)  # a NaN is above every edge, as in Spark
    else:
        out = (np.searchsorted(edges, x) + 1).astype(np.uint8)
    if values.null_count:
        out[values.is_null().to_numpy(zero_copy_only=False)] = 0
    return out


def gradient_blocks(df: DataFrame, packing: Packing, edges: list[list[float]], base: float, bits: dict[int, tuple[str, int]] | None = None) -> DataFrame:
    """Arrow batches of features x0, x1, ... and y as a row each: packed codes, and gradients of the constant ``base``."""
    bits = bits or {}

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                codes = packing.packed([bins_of(numbers_of(batch, i, bits), e) for i, e in enumerate(edges)])
                gradient = base - batch.column("y").to_numpy(zero_copy_only=False)
                yield pa.RecordBatch.from_pydict({"codes": [codes.tobytes()], "gradient": [gradient.tobytes()]})

    return df.mapInArrow(pack, "codes binary, gradient binary")


def unpacked(batches: Iterator[pa.RecordBatch], packing: Packing) -> Iterator[tuple[bytes, np.ndarray, np.ndarray]]:
    for batch in batches:
        for raw, gradient in zip(batch.column("codes").to_pylist(), batch.column("gradient").to_pylist()):
            yield raw, np.frombuffer(raw, np.uint16).reshape(len(packing.totals), -1), np.frombuffer(gradient)


def moved_on(blocks: DataFrame, packing: Packing, trees: list) -> DataFrame:
    """The blocks with gradients after ``trees``."""

    def move(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values = [packing.values_of(t) for t in trees]
        for raw, codes, g in unpacked(batches, packing):
            for v in values:
                g = g + v(codes)
            yield pa.RecordBatch.from_pydict({"codes": [raw], "gradient": [g.tobytes()]})

    return blocks.mapInArrow(move, "codes binary, gradient binary")


def histograms(blocks: DataFrame, packing: Packing, width: int, trees: list, growing: list[tuple], parts: list[tuple]) -> list[np.ndarray]:
    """Sums of gradient and rows by (feature, bin) for parts of the frontier: one pass over the blocks.

    A part is a node, or with (feature, bin, missing left, side) the rows of a
    node that its split would send to one side.  ``trees`` are those since the
    gradients were last kept.
    """
    return histograms_of_fits(blocks, packing, width, [(trees, growing, parts)])[0]


def histograms_of_fits(blocks: DataFrame, packing: Packing, width: int, asked: list[tuple], tasks: int | None = None) -> list[list[np.ndarray]]:
    """``histograms`` for what several fits ask for, (trees, growing, parts) each, in one pass."""
    n_parts = sum(len(parts) for *_, parts in asked)
    shape = (n_parts, len(packing.sizes), width, 2)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fits = [([packing.values_of(t) for t in trees], packing.finder(growing, np.arange(len(growing), dtype=np.int16)), [(p, packing.empty()) for p in parts]) for trees, growing, parts in asked]
        for _, codes, first in unpacked(batches, packing):
            for values, leaf_of, sums in fits:
                g = first
                for v in values:
                    g = g + v(codes)
                leaf = leaf_of(codes)
                for (node, split), total in sums:
                    mine = leaf == node
                    if split is not None:
                        f, b, missing_left, left = split
                        mine &= packing.goes_left(codes, f, b, missing_left) == left
                    if mine.all():
                        packing.count(total, codes, g)
                    else:
                        at = np.flatnonzero(mine)
                        packing.count(total, codes[:, at], g[at])
        out = np.array([packing.by_feature(total, width) for *_, sums in fits for _, total in sums])
        yield pa.RecordBatch.from_pydict({"b": pa.array([0], pa.int32()), "m": [out.tobytes()]})

    total = summed(blocks.mapInArrow(partial, "b int, m binary"), tasks, 8.0 * np.prod(shape)).get(0, np.zeros(shape)).reshape(shape)
    ends = np.cumsum([len(parts) for *_, parts in asked])
    return [list(total[end - len(parts) : end]) for end, (*_, parts) in zip(ends, asked)]


class Binned:
    """Rows of a training set as blocks of bins, kept once for all fits over them.

    A fit asks for histograms inside ``with``; once every fit inside waits for
    its own, one pass over the blocks makes them all.
    """

    def __init__(self, df: DataFrame, features: list[str], target: str, bins: int):
        self.edges = bin_edges(df, features, bins)
        self.width = max([bins, *[len(e) + 1 for e in self.edges]]) + 1
        self.packing = Packing([len(e) + 2 for e in self.edges])
        own, bits = numbered(df, features, [F.col(f"`{target}`").cast("double").alias("y")])
        n_rows, base = df.agg(F.count(F.lit(1)), F.avg(target)).first()
        self.base, self.tasks = float(base or 0.0), max(1, n_rows // TASK_ROWS)
        self.data = gradient_blocks(own, self.packing, self.edges, self.base, bits).coalesce(self.tasks).persist()
        self.turn = threading.Condition()
        self.fits, self.asked = 0, []

    def unpersist(self) -> None:
        self.data.unpersist()

    def __enter__(self) -> "Binned":
        with self.turn:
            self.fits += 1
        return self

    def __exit__(self, *_: object) -> None:
        with self.turn:
            self.fits -= 1
            self.turn.notify_all()

    def histograms(self, trees: list, growing: list[tuple], parts: list[tuple]) -> list[np.ndarray]:
        told: Future = Future()
        with self.turn:
            self.asked.append((told, (list(trees), list(growing), parts)))
            self.turn.notify_all()
            self.turn.wait_for(lambda: told.done() or len(self.asked) >= self.fits)
            mine: list[tuple] = []
            if not told.done():
                mine, self.asked = self.asked, mine
        if mine:
            try:
                for (f, _), h in zip(mine, histograms_of_fits(self.data, self.packing, self.width, [a for _, a in mine], self.tasks)):
                    f.set_result(h)
            except BaseException as e:
                for f, _ in mine:
                    if not f.done():
                        f.set_exception(e)
            with self.turn:
                self.turn.notify_all()
        return told.result()


def best_split(h: np.ndarray, lam: float, min_rows: int = 1, missing: bool = False) -> tuple:
    """(gain, feature, bin): ties go to the lowest feature, then the lowest bin.

    With ``missing``, bin 0 holds rows without a value and the fourth part says
    whether they go left; both ways are tried, left first.
    """
    if missing:
        ways = [best_split(h, lam, min_rows), best_split(np.concatenate([h[:, 1:], h[:, :1]], 1), lam, min_rows)]
        if round(ways[1][0], 6) > round(ways[0][0], 6):
            gain, f, b = ways[1]
            return gain, f, b + 1, False
        return *ways[0], True
    g, n = h[0, :, 0].sum(), h[0, :, 1].sum()
    left = np.cumsum(h, axis=1)
    lg, ln = left[:, :-1, 0], left[:, :-1, 1]
    gain = 0.5 * (lg**2 / (ln + lam) + (g - lg) ** 2 / (n - ln + lam) - g**2 / (n + lam))
    gain = np.where((ln >= min_rows) & (n - ln >= min_rows), gain, -np.inf)
    at = int(np.argmax(np.round(gain, 6)))
    return float(gain.flat[at]), at // gain.shape[1], at % gain.shape[1]


def goes_left(column: Column, b: int, missing_left: bool) -> Column:
    """Whether a binned column's row goes left of a split."""
    return (column <= b) if missing_left else (column <= b) & (column > 0)


def boost(df: DataFrame, features: list[str], target: str, *, growth: str = "level", trees: int = 8, depth: int = 3, leaves: int = 8, eta: float = 0.3, lam: float = 1.0, gamma: float = 0.0, bins: int = 16, shared: Binned | None = None) -> dict:
    """Squared-loss boosting on histograms, growing by level or by best leaf.

    Only the smaller child of a split is scanned; its sibling is the difference,
    and children that stay leaves need no scan, as their parent's sums tell theirs.
    By leaf a pass also scans the children of the next best leaves, for later.
    Rows carry the gradient after earlier trees, brought up to date every few trees.
    ``shared`` has the rows in bins, where other fits use them too.
    """
    own = shared or Binned(df, features, target, bins)
    kept: DataFrame | None = None  # blocks of this fit alone, once their gradients are its own
    value = lambda x: float(-eta * x[0, :, 0].sum() / (x[0, :, 1].sum() + lam))
    recent: list[list[tuple]] = []

    def scan(tree: list[tuple], parts: list[tuple]) -> list[np.ndarray]:
        if kept is not None:
            return histograms_of_fits(kept, own.packing, own.width, [(recent, tree, parts)], own.tasks)[0]
        return own.histograms(recent, tree, parts)

    def grow() -> list[tuple]:
        tree: list[tuple] = [(-1, 0, 0, 0, 0.0, True)]
        root = scan(tree, [(0, None)])[0]
        frontier = [(-best_split(root, lam, missing=True)[0], 0, root)]
        scanned: dict[int, tuple] = {}
        n_leaves, level = 1, 0
        while frontier and (level < depth if growth == "level" else n_leaves < leaves):
            last = level + 1 == depth if growth == "level" else n_leaves + 1 == leaves
            if growth == "level":
                take, frontier = sorted(frontier, key=lambda x: x[1]), []
                ahead = take
            else:
                take = [heapq.heappop(frontier)]
                ahead = [*take, *heapq.nsmallest(LEAVES_AHEAD, frontier)]
            splits = {}
            for _, node, hist in take if last else ahead:
                gain, f, b, missing_left = best_split(hist, lam, missing=True)
                if node not in scanned and gain > gamma and np.isfinite(gain):
                    n_low = hist[f, (0 if missing_left else 1) : b + 1, 1].sum()
                    splits[node] = (f, b, missing_left, bool(2 * n_low <= hist[f, :, 1].sum()))
            if last:
                for _, node, hist in take:
                    if node in splits:
                        f, b, missing_left, left = splits[node]
                        low = hist[f, (0 if missing_left else 1) : b + 1].sum(0)
                        scanned[node] = (splits[node], (low if left else hist[f].sum(0) - low).reshape(1, 1, 2))
            elif any(node in splits for _, node, _ in take):
                for (node, split), small in zip(splits.items(), scan(tree, list(splits.items()))):
                    scanned[node] = (split, small)
            for _, node, hist in take:
                if node not in scanned:
                    tree[node] = (-1, 0, 0, 0, value(hist), True)
                    continue
                (f, b, missing_left, left), small = scanned[node]
                low, high = len(tree), len(tree) + 1
                tree += [(-1, 0, 0, 0, 0.0, True)] * 2
                tree[node] = (f, b, low, high, 0.0, missing_left)
                n_leaves += 1
                rest = (hist if small.shape == hist.shape else hist[f].sum(0).reshape(1, 1, 2)) - small
                for child, got in ((low, small if left else rest), (high, rest if left else small)):
                    heapq.heappush(frontier, (0.0 if last else -best_split(got, lam, missing=True)[0], child, got))
            level += 1
        for _, node, hist in frontier:
            tree[node] = (-1, 0, 0, 0, value(hist), True)
        return tree

    try:
        grown: list[list[tuple]] = []
        with own:
            while len(grown) < min(trees, GRADIENT_TREES):
                grown.append(grow())
                recent.append(grown[-1])
        while len(grown) < trees:
            if len(recent) == GRADIENT_TREES:
                before, kept, recent = kept, moved_on(own.data if kept is None else kept, own.packing, recent).persist(), []
                kept.count()
                if before is not None:
                    before.unpersist()
            grown.append(grow())
            recent.append(grown[-1])
        return {"kind": "trees", "base": own.base, "edges": own.edges, "trees": grown}
    finally:
        if kept is not None:
            kept.unpersist()
        if shared is None:
            own.unpersist()


def binned_case(tree: list[tuple], at: int) -> Column:
    """A tree over binned columns."""
    f, b, left, right, value, missing_left = tree[at]
    if f < 0:
        return F.lit(value)
    return F.when(goes_left(F.col(f"b{f}"), b, missing_left), binned_case(tree, left)).otherwise(binned_case(tree, right))


def mllib_boost(df: DataFrame, features: list[str], target: str, *, trees: int = 8, depth: int = 3, eta: float = 0.3, bins: int = 16, leaves: int = 8, **_: object) -> dict:
    """The JVM library's boosted trees; its fitted model is used as it is, not converted."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import GBTRegressor

    rows = VectorAssembler(inputCols=features, outputCol="_x").transform(df.select(*features, F.col(target).cast("double").alias("_y")))
    most = depth if leaves >= 2**depth else max(1, leaves.bit_length() - 1)
    model = GBTRegressor(featuresCol="_x", labelCol="_y", maxIter=trees, maxDepth=most, stepSize=eta, maxBins=max(bins, 8), seed=1).fit(rows)
    return {"kind": "mllib", "model": model, "features": features}


def mllib_linear(df: DataFrame, features: list[str], target: str, alpha: float, rho: float | None = None) -> dict:
    """The JVM library's linear regression, brought to the same loss as the moments' solvers.

    ``rho`` None is ridge with alpha on the sum of squares, else an elastic net on the mean.
    Its penalty on squares is scaled by the target's deviation, that on absolute values is not.
    """
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import LinearRegression

    rows = VectorAssembler(inputCols=features, outputCol="_x").transform(df.select(*features, F.col(target).cast("double").alias("_y")))
    n, sd = rows.agg(F.count(F.lit(1)), F.stddev_samp("_y")).first()
    sd = sd or 1.0
    l1, l2 = (0.0, alpha / n * sd) if rho is None else (alpha * rho, alpha * (1 - rho) * sd)
    share = l1 / (l1 + l2) if l1 + l2 else 0.0
    model = LinearRegression(featuresCol="_x", labelCol="_y", standardization=False, regParam=l1 + l2, elasticNetParam=share, tol=1e-10, maxIter=500, solver="normal" if not l1 else "auto").fit(rows)
    return {"kind": "linear", "w": list(map(float, model.coefficients)), "b": float(model.intercept)}


def predicted(df: DataFrame, model: dict, features: list[str], out: str = "prediction") -> DataFrame:
    """``df`` with the predictions of a model of any kind."""
    if model["kind"] == "mllib":
        from pyspark.ml.feature import VectorAssembler

        wide = VectorAssembler(inputCols=features, outputCol="_x").transform(df)
        return model["model"].transform(wide).withColumnRenamed("prediction", out).drop("_x")
    if model["kind"] == "perceptron":
        return df.withColumn(out, perceptron_column(model, features))
    return df.withColumn(out, prediction(model, features))


def prediction(model: dict, features: list[str]) -> Column:
    """A model as one expression: a sum of products, or nested cases of trees."""
    if model["kind"] in ("linear", "logistic"):
        out = F.lit(model["b"])
        for c, w in zip(features, model["w"]):
            out = out + F.col(c) * F.lit(w)
        return 1 / (1 + F.exp(-out)) if model["kind"] == "logistic" else out
    if model["kind"] == "mean":
        return F.lit(model["value"])

    def case(tree: list[tuple], at: int) -> Column:
        f, b, left, right, value, missing_left = tree[at]
        if f < 0:
            return F.lit(value)
        edges, c = model["edges"][f], F.col(features[f])
        under = F.lit(False) if b == 0 else F.lit(True) if b > len(edges) else c <= edges[b - 1]
        goes = F.when(c.isNull(), F.lit(missing_left)).otherwise(under)
        return F.when(goes, case(tree, left)).otherwise(case(tree, right))

    out = F.lit(model["base"])
    for tree in model["trees"]:
        out = out + case(tree, 0)
    return out


def regression_measures(target: str, predicted: str = "prediction") -> dict[str, Column]:
    e = F.col(predicted) - F.col(target)
    return {
        "rmse": F.sqrt(F.avg(e * e)), "mae": F.avg(F.abs(e)),
        "r2": 1 - F.sum(e * e) / (F.sum(F.col(target).cast("double") * F.col(target)) - F.sum(F.col(target).cast("double")) * F.avg(target)),
        "rows": F.count(F.lit(1)).cast("double"),
    }


def class_measures(target: str, probability: str) -> dict[str, Column]:
    y, p = F.col(target), F.col(probability)
    hit = (p > 0.5).cast("int")
    tp = F.sum(hit * y)
    return {
        "accuracy": F.avg((hit == y).cast("double")),
        "logloss": -F.avg(F.when(y == 1, F.log(F.greatest(p, F.lit(1e-15)))).otherwise(F.log(F.greatest(1 - p, F.lit(1e-15))))),
        "f1": 2 * tp / (F.sum(hit) + F.sum(y)),
    }


def ensemble_weights(m: np.ndarray, how: str = "mean", rounds: int = 20) -> np.ndarray:
    """Weights of members from the moments of (1, predictions, target)."""
    k = len(m) - 2
    if how == "mean":
        return np.full(k, 1 / k)
    error = lambda w: float(np.array([0, *w, -1]) @ m @ np.array([0, *w, -1]))
    if how == "weighted":
        inverse = np.array([1 / max(error(np.eye(k)[i]), 1e-12) for i in range(k)])
        return inverse / inverse.sum()
    if how == "stack":
        return np.linalg.lstsq(m[1:-1, 1:-1], m[1:-1, -1], rcond=None)[0]
    counts = np.zeros(k)
    for _ in range(rounds):
        best = min(range(k), key=lambda i: error((counts + np.eye(k)[i]) / (counts.sum() + 1)))
        counts[best] += 1
    return counts / counts.sum()


def gram(df: DataFrame, column: str) -> np.ndarray:
    """XᵀX of an array column by partial sums, merged in parallel."""

    def partial(batches):
        total = 0
        for pdf in batches:
            x = np.stack(pdf[column].to_numpy()).astype(float) if len(pdf) else np.zeros((0, 1))
            total = total + x.T @ x
        if not np.isscalar(total):
            yield pd.DataFrame({"b": [0], "m": [total.tobytes()]})

    g = summed(df.select(column).mapInPandas(partial, "b int, m binary")).get(0, np.zeros(1))
    return g.reshape(int(len(g) ** 0.5), -1)


def shrink(rows: np.ndarray, size: int) -> np.ndarray:
    _, s, v = np.linalg.svd(rows, full_matrices=False)
    cut = s[size] ** 2 if len(s) > size else 0.0
    kept = np.sqrt(np.maximum(s[:size] ** 2 - cut, 0))
    return (kept[:, None] * v[:size])[kept > 0]


def frequent_directions(df: DataFrame, column: str, size: int) -> np.ndarray:
    """A sketch of ``size`` rows a task, merged by stacking and shrinking."""

    def partial(batches):
        b = None
        for pdf in batches:
            x = np.stack(pdf[column].to_numpy()).astype(float) if len(pdf) else None
            for k in range(0, 0 if x is None else len(x), size):
                part = x[k : k + size]
                b = part if b is None else np.vstack([b, part])
                if len(b) > size:
                    b = shrink(b, size)
        if b is not None:
            yield pd.DataFrame({"n": [b.shape[1]], "b": [b.tobytes()]})

    def fold(batches):
        out, n = None, 0
        for pdf in batches:
            for n, raw in zip(pdf["n"], pdf["b"]):
                b = np.frombuffer(raw).reshape(-1, n)
                out = shrink(b if out is None else np.vstack([out, b]), size)
        if out is not None:
            yield pd.DataFrame({"n": [n], "b": [out.tobytes()]})

    out = None
    for r in merged(df.select(column).mapInPandas(partial, "n int, b binary"), "n int, b binary", fold):
        b = np.frombuffer(r["b"]).reshape(-1, r["n"])
        out = shrink(b if out is None else np.vstack([out, b]), size)
    return out


def truncated_svd(df: DataFrame, column: str, k: int, method: str = "gram", size: int | None = None, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Singular values and right vectors: exact by the Gram matrix, a sketch, randomised, or by the JVM library."""
    if method == "mllib":
        return mllib_svd(df, column, k)
    if method == "freq_dir":
        _, s, v = np.linalg.svd(frequent_directions(df, column, size or 2 * k), full_matrices=False)
        return s[:k], v[:k].T
    g = gram(df, column)
    if method == "randomized":
        q = np.linalg.qr(g @ np.random.default_rng(seed).normal(size=(len(g), min(len(g), k + 8))))[0]
        values, u = np.linalg.eigh(q.T @ g @ q)
        order = np.argsort(-values)[:k]
        return np.sqrt(np.maximum(values[order], 0)), q @ u[:, order]
    values, v = np.linalg.eigh(g)
    order = np.argsort(-values)[:k]
    return np.sqrt(np.maximum(values[order], 0)), v[:, order]


def mllib_svd(df: DataFrame, column: str, k: int) -> tuple[np.ndarray, np.ndarray]:
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.linalg.distributed import RowMatrix

    rows = df.select(F.transform(column, lambda x: x.cast("double")).alias("x")).rdd.map(lambda r: Vectors.dense(r["x"]))
    found = RowMatrix(rows).computeSVD(k)
    return np.array(found.s.toArray()), np.array(found.V.toArray())


def perceptron(df: DataFrame, features: list[str], target: str, *, hidden: int = 4, epochs: int = 50, seed: int = 1) -> dict:
    """A small network for two classes by the JVM library; its weights come back as plain arrays."""
    from pyspark.ml.classification import MultilayerPerceptronClassifier
    from pyspark.ml.feature import VectorAssembler

    rows = VectorAssembler(inputCols=features, outputCol="_x").transform(df.select(*features, F.col(target).cast("double").alias("_y")))
    p = len(features)
    fitted = MultilayerPerceptronClassifier(featuresCol="_x", labelCol="_y", layers=[p, hidden, 2], maxIter=epochs, seed=seed).fit(rows)
    w = np.array(fitted.weights.toArray())
    one, rest = w[: p * hidden].reshape(hidden, p, order="F"), w[p * hidden :]
    two = rest[hidden : hidden + 2 * hidden].reshape(2, hidden, order="F")
    return {"kind": "perceptron", "w1": one, "b1": rest[:hidden], "w2": two, "b2": rest[3 * hidden :]}


def perceptron_column(model: dict, features: list[str]) -> Column:
    """The probability of class 1 as one expression: sigmoid units, then a softmax."""
    units = []
    for w, b in zip(model["w1"], model["b1"]):
        z = F.lit(float(b))
        for c, k in zip(features, w):
            z = z + F.col(c) * F.lit(float(k))
        units.append(1 / (1 + F.exp(-z)))
    out = []
    for w, b in zip(model["w2"], model["b2"]):
        z = F.lit(float(b))
        for u, k in zip(units, w):
            z = z + u * F.lit(float(k))
        out.append(z)
    return 1 / (1 + F.exp(out[0] - out[1]))


def quantize(vector: Column) -> Column:
    """8-bit integers and their scale; a vector of zeros has scale 0."""
    most = F.array_max(F.transform(vector, lambda x: F.abs(x)))
    scale = most / 127
    return F.struct(F.transform(vector, lambda x: F.when(scale > 0, F.round(x / scale)).otherwise(0).cast("int")).alias("q"), scale.alias("scale"))


def prune_weights(weights: np.ndarray, share: float) -> np.ndarray:
    """The smallest weights, by magnitude, set to zero."""
    cut = np.sort(np.abs(weights).ravel())[int(share * weights.size)] if share < 1 else np.inf
    return np.where(np.abs(weights) < cut, 0, weights)
