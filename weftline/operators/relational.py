"""Joins and groupings that Spark has no single call for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str, out: str, tie: str) -> DataFrame:
    """For each left row the last right value at or before its time: one union and one window.

    ``by``, ``on`` and ``tie`` (what orders equal times) exist on both sides.
    """
    both = left.withColumns({"_right": F.lit(0), out: F.lit(None).cast(right.schema[value].dataType)}).unionByName(
        right.select(by, on, tie, F.col(value).alias(out)).withColumn("_right", F.lit(1)), allowMissingColumns=True
    )
    order = Window.partitionBy(by).orderBy(on, F.desc("_right"), tie).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(out, F.last(out, ignorenulls=True).over(order)).filter("_right = 0").drop("_right")


def range_join(left: DataFrame, right: DataFrame, point: str, low: str, high: str, width: float, how: str = "inner") -> DataFrame:
    """Points in [low, high) through buckets of ``width``: an equi-join instead of all pairs."""
    spans = right.withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return left.withColumn("_bucket", F.floor(F.col(point) / width)).join(spans, "_bucket", how).filter(
        (F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))
    ).drop("_bucket")


def interval_join(left: DataFrame, right: DataFrame, by: str, left_ts: str, right_ts: str, seconds: int) -> DataFrame:
    """Pairs of one key whose times are at most ``seconds`` apart, later on the right; bucketed by time."""
    at = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / seconds)
    near = left.withColumn("_b", F.explode(F.array(at(left_ts), at(left_ts) + 1)))
    own = right.withColumn("_b", at(right_ts)).withColumnRenamed(by, f"_{by}")
    met = near.join(own, (near[by] == own[f"_{by}"]) & (near["_b"] == own["_b"]))
    limit = F.col(left_ts) + F.expr(f"INTERVAL {seconds} SECONDS")
    return met.filter((F.col(right_ts) > F.col(left_ts)) & (F.col(right_ts) <= limit)).drop("_b", f"_{by}")


def salted_join(left: DataFrame, right: DataFrame, on: str, salts: int, spread: str) -> DataFrame:
    """A hot key's left rows go to ``salts`` partitions; the right side is repeated for them."""
    l = left.withColumn("_salt", F.pmod(F.hash(spread), F.lit(salts)))  # noqa: E741
    r = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return l.join(r, [on, "_salt"]).drop("_salt")


def top_k_per_group(df: DataFrame, by: str, order: list[Column], k: int) -> DataFrame:
    return df.withColumn("_n", F.row_number().over(Window.partitionBy(by).orderBy(*order))).filter(F.col("_n") <= k).drop("_n")


def sessionize(df: DataFrame, by: str, ts: str, tie: str, gap_seconds: int) -> DataFrame:
    """Numbers the sessions of each key: a gap of more than ``gap_seconds`` begins one."""
    w = Window.partitionBy(by).orderBy(ts, tie)
    new = (F.col(ts) > F.lag(ts).over(w) + F.expr(f"INTERVAL {gap_seconds} SECONDS")).cast("int")
    return df.withColumn("_new", F.coalesce(new, F.lit(1))).withColumn("session", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("_new")
