"""Statistics of sorted columns without one task that sorts: exact quantiles and areas under curves."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Distinct values in a range up to which their counts are collected, and the sketch's accuracy.
MOST_VALUES = 100_000
ACCURACY = 10_000
#: From the least double to what Spark sorts last.
EVERYTHING = (-math.inf, math.nan)
#: Ranges that scores are cut into; their totals are the only rows sorted in one task.
RANGES = 128


def exact_quantiles(df: DataFrame, columns: list[str], share: float = 0.5) -> dict[str, float | None]:
    """The interpolating quantile of each column; null where a column has no value.

    Columns of few distinct values are counted by value.  For the others a sketch
    gives a range that holds the two ranks wanted; values in it are counted by
    value and those below it as one, in a single pass for all columns.
    A range with too many distinct values is narrowed by a sketch of its own.
    """
    numbers = df.select(*[F.col(f"`{c}`").cast("double").alias(f"x{k}") for k, c in enumerate(columns)])
    names = {f"x{k}": c for k, c in enumerate(columns)}
    out: dict[str, float | None] = dict.fromkeys(columns)
    around = [max(0.0, share - 3 / ACCURACY), min(1.0, share + 3 / ACCURACY)]
    told = numbers.agg(*[F.struct(F.count(x).alias("n"), F.approx_count_distinct(x).alias("d")).alias(x) for x in names]).first()
    ranges = {x: EVERYTHING for x in names}
    many = [x for x in names if told[x]["d"] > MOST_VALUES / 2]  # the estimate is some per cent off
    if many:
        found = numbers.agg(*[F.percentile_approx(x, around, ACCURACY).alias(x) for x in many]).first()
        ranges |= {x: tuple(found[x]) for x in many}
    wanted = {x: (share * (told[x]["n"] - 1), *ranges[x]) for x in names if told[x]["n"]}
    while wanted:
        parts = F.array(*[F.struct(F.lit(x).alias("x"), F.col(x).alias("v"), F.lit(low).alias("low"), F.lit(high).alias("high")) for x, (_, low, high) in wanted.items()])
        long = numbers.select(F.explode(parts).alias("r")).select("r.*").filter("v is not null")
        inside = long.filter("v <= high").groupBy("x", F.when(F.col("v") >= F.col("low"), F.col("v")).alias("v")).agg(F.count("*").alias("n"))
        rows = inside.orderBy("x", F.col("v").asc_nulls_first()).limit((MOST_VALUES + 2) * len(wanted)).collect()
        beyond = long.filter("v > high").groupBy("x").agg(F.min("v").alias("v")).collect() if any(r[1:] != EVERYTHING for r in wanted.values()) else []
        following = {r["x"]: r["v"] for r in beyond}
        left = {}
        for x, (rank, low, high) in wanted.items():
            mine = [(r["v"], r["n"]) for r in rows if r["x"] == x]
            if len(mine) > MOST_VALUES:
                left[x] = narrowed(numbers, x, rank, low, high)
                continue
            below = sum(n for v, n in mine if v is None)
            ends, total = [], below
            for v, n in mine:
                if v is not None:
                    total += n
                    ends.append((total, v))
            at = math.floor(rank)
            first, second = (next((v for end, v in ends if end > k), following.get(x)) for k in (at, at + 1))
            out[names[x]] = first if rank == at or second is None else first + (rank - at) * (second - first)
        wanted = left
    return out


def narrowed(numbers: DataFrame, x: str, rank: float, low: float, high: float) -> tuple[float, float, float]:
    """The same rank with a range that a sketch of the values in the old one gives."""
    below, inside = numbers.agg(F.count_if(F.col(x) < low), F.count_if(F.col(x).between(low, high))).first()
    share = min(1.0, max(0.0, (rank - below) / max(1, inside - 1)))
    around = [max(0.0, share - 3 / ACCURACY), min(1.0, share + 3 / ACCURACY)]
    e = numbers.filter(F.col(x).between(low, high)).agg(F.percentile_approx(x, around, ACCURACY)).first()[0]
    return rank, e[0], e[1]


def auc(df: DataFrame, target: str, score: str) -> DataFrame:
    """Area under the curve from counts by distinct score; ties count half.

    Scores are cut into ranges; the negatives of lower ranges come from the few
    totals of ranges, those of the own range from a window inside it.
    """
    by = df.groupBy(F.col(score).cast("double").alias("s")).agg(F.sum(target).cast("double").alias("pos"), F.sum(1 - F.col(target)).cast("double").alias("neg"))
    edges = by.agg(F.percentile_approx("s", [k / RANGES for k in range(1, RANGES)], ACCURACY)).first()[0] or []
    cuts = F.array(*[F.lit(e) for e in sorted(set(edges))]).cast("array<double>")
    ranged = by.withColumn("range", F.size(F.filter(cuts, lambda e: e < F.col("s"))))
    totals = ranged.groupBy("range").agg(F.sum("neg").alias("in_range"))
    lower = totals.select("range", F.coalesce(F.sum("in_range").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)).alias("lower"))
    inside = F.sum("neg").over(Window.partitionBy("range").orderBy("s").rowsBetween(Window.unboundedPreceding, -1))
    placed = ranged.withColumn("inside", F.coalesce(inside, F.lit(0.0))).join(F.broadcast(lower), "range")
    below = F.col("lower") + F.col("inside")
    return placed.agg((F.sum(F.col("pos") * (below + F.col("neg") / 2)) / (F.sum("pos") * F.sum("neg"))).alias("auc"))
