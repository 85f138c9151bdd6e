"""Profiles of tables: one pass for all columns, unpivoted to (column, statistic, value)."""

from __future__ import annotations

from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .order import exact_quantiles


def unpivoted(row: DataFrame, names: dict[str, tuple]) -> DataFrame:
    """One-row aggregates to rows; names: aggregate to its labels."""
    rows = F.array(*[F.struct(*[F.lit(x).alias(f"k{i}") for i, x in enumerate(labels)], F.col(f"`{a}`").cast("double").alias("value")) for a, labels in names.items()])
    return row.select(F.explode(rows).alias("r")).select("r.*")


def numeric_columns(df: DataFrame) -> list[str]:
    return [c for c, t in df.dtypes if t in ("int", "bigint", "double", "float") or t.startswith("decimal")]


def profile_missing(df: DataFrame, columns: list[str] | None = None) -> DataFrame:
    cols = columns or df.columns
    aggs = [F.avg(F.col(c).isNull().cast("double")).alias(c) for c in cols]
    return unpivoted(df.agg(*aggs), {c: (c,) for c in cols}).withColumnRenamed("k0", "column_name").withColumnRenamed("value", "missing_ratio")


def profile_cardinality(df: DataFrame, columns: list[str], exact: bool = True) -> DataFrame:
    """Exact counts expand every row by column; beyond some size take the sketch."""
    count = F.count_distinct if exact else F.approx_count_distinct
    aggs = [count(F.col(c)).alias(c) for c in columns]
    out = unpivoted(df.agg(*aggs), {c: (c,) for c in columns})
    return out.select(F.col("k0").alias("column_name"), F.col("value").cast("bigint").alias("n_distinct"))


def tokens(df: DataFrame, column: str) -> DataFrame:
    words = F.split(F.lower(F.trim(F.col(column))), r"[ \t\n\r\f\x0B]+")
    return df.select(F.explode(words).alias("token")).filter("token <> ''")


def profile_vocabulary(df: DataFrame, column: str) -> DataFrame:
    """Tokens, types, their ratio and the share of types that occur once."""
    counts = tokens(df, column).groupBy("token").agg(F.count("*").alias("n"))
    return counts.agg(
        F.sum("n").alias("n_tokens"), F.count("*").alias("n_types"),
        F.round(F.count("*") / F.sum("n"), 6).alias("type_token_ratio"),
        F.round(F.avg((F.col("n") == 1).cast("double")), 6).alias("hapax_share"),
    )


def numeric_statistics(c: str) -> dict[str, Column]:
    x = F.col(c).cast("double")
    return {"min": F.min(x) + 0.0, "max": F.max(x), "mean": F.round(F.avg(x), 4), "std": F.round(F.stddev_pop(x), 4)}


def profile_numeric(df: DataFrame, columns: list[str] | None = None) -> DataFrame:
    cols = columns or numeric_columns(df)
    aggs = {f"{c}|{s}": col for c in cols for s, col in numeric_statistics(c).items()}
    medians = exact_quantiles(df, cols)
    row = df.agg(*[v.alias(k) for k, v in aggs.items()]).withColumns({f"{c}|median": F.lit(v).cast("double") for c, v in medians.items()})
    out = unpivoted(row, {k: tuple(k.split("|")) for k in (*aggs, *[f"{c}|median" for c in medians])})
    return out.select(F.col("k0").alias("column_name"), F.col("k1").alias("statistic"), "value")


def top_values(df: DataFrame, column: str, k: int = 5) -> DataFrame:
    return df.groupBy(F.col(column).alias("value")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "value").limit(k)


def profile_dense(df: DataFrame, column: str) -> DataFrame:
    norm = F.sqrt(F.aggregate(column, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
    return df.agg(F.min(F.size(column)).alias("min_size"), F.max(F.size(column)).alias("max_size"), F.round(F.avg(norm), 4).alias("mean_norm"))


def hash_sample(df: DataFrame, key: str, share: int, out_of: int = 100, salt: int = 7) -> DataFrame:
    """Rows whose key falls below the share; samples of growing shares are nested."""
    return df.filter((F.col(key) * 7919 + salt) % out_of < share)


def profile_all(tables: dict[str, DataFrame]) -> DataFrame:
    """Rows, nulls and distinct values of every column of every table: a scan a table."""
    parts = []
    for name, df in sorted(tables.items()):
        plain = [c for c, t in df.dtypes if not t.startswith(("array", "map", "struct"))]
        aggs = {f"{c}|{s}": col for c in plain for s, col in {"rows": F.count(F.lit(1)), "nulls": F.count_if(F.col(c).isNull()), "distinct": F.approx_count_distinct(c)}.items()}
        row = df.agg(*[v.alias(k) for k, v in aggs.items()])
        parts.append(unpivoted(row, {k: (name, *k.split("|")) for k in aggs}))
    out = reduce(DataFrame.unionAll, parts)
    return out.select(F.col("k0").alias("table_name"), F.col("k1").alias("column_name"), F.col("k2").alias("statistic"), "value")


def infer_task(df: DataFrame, target: str, most_classes: int = 20) -> str:
    kind = dict(df.dtypes)[target]
    if kind in ("string", "boolean"):
        return "classification"
    few = df.agg(F.approx_count_distinct(target)).first()[0] <= most_classes
    return "classification" if few and kind in ("int", "bigint", "tinyint", "smallint") else "regression"


def match_entities(a: DataFrame, b: DataFrame, key: str, block: Column, threshold: float) -> DataFrame:
    """Pairs of one block whose normalised edit distance passes the threshold.

    Candidates come from shared rare characters, not from the block, so a block that holds many values is no join of all its pairs.
    """
    other = F.expr(block._jc.toString().replace("left_value", "right_value"))
    return match_everywhere(a, b, key, threshold).filter(block == other)


#: Values of one cut of a token's group; a cell of the join holds two cuts.
CUT_VALUES = 1_000


def match_everywhere(a: DataFrame, b: DataFrame, key: str, threshold: float, cut_values: int = CUT_VALUES) -> DataFrame:
    """All pairs whose normalised edit distance passes the threshold, wherever their letters are.

    With m characters in the longer value, d edits leave m - d in common, each
    counted as often as both have it.  Of characters numbered within their value
    and set in one order, rare ones first, a pair so shares one among the first
    d + 1 of both values; it is judged at the first that it shares, if the lengths
    allow it.  Characters of many values are cut, and each two cuts meet apart.
    """
    if not 0.01 <= threshold <= 1:
        raise ValueError("threshold must be from 0.01 to 1")

    def edits(length: Column) -> Column:
        return F.floor(length * (1 - threshold + 5e-7) + 1e-9).cast("int")  # the similarity is rounded to six places

    sides = a.select(F.col(key).alias("value"), F.lit(True).alias("in_a"), F.lit(False).alias("in_b")).unionAll(
        b.select(F.col(key).alias("value"), F.lit(False).alias("in_a"), F.lit(True).alias("in_b"))
    )
    values = sides.filter("value <> ''").groupBy("value").agg(F.max("in_a").alias("in_a"), F.max("in_b").alias("in_b"))
    letters = values.select("*", F.explode(F.expr("transform(sequence(1, length(value)), i -> substring(value, i, 1))")).alias("letter"))
    counted = letters.groupBy("value", "in_a", "in_b", "letter").count()
    tokens = counted.select("value", "in_a", "in_b", F.explode(F.expr("transform(sequence(1L, count), k -> concat(letter, k))")).alias("token"))
    ordered = tokens.join(tokens.groupBy("token").count(), "token").groupBy("value", "in_a", "in_b").agg(
        F.array_sort(F.collect_list(F.struct("count", "token"))).alias("own")
    )
    first = ordered.withColumn("n", F.length("value")).withColumn("own", F.slice("own", F.lit(1), edits(F.col("n")) + 1))
    cut = first.select("*", F.explode("own").alias("t")).withColumn("n_cuts", F.ceil(F.col("t.count") / cut_values))
    cut = cut.withColumn("cut", F.pmod(F.xxhash64("value"), "n_cuts")).withColumn("other", F.explode(F.expr("sequence(0L, n_cuts - 1)")))
    cells = cut.select("value", "in_a", "in_b", "n", F.col("own.token").alias("own"), F.col("t.token").alias("token"), "cut", F.least("cut", "other").alias("low"), F.greatest("cut", "other").alias("high"))
    left, right = (cells.select("token", "low", "high", *[F.col(c).alias(f"{side}_{c}") for c in ("value", "in_a", "in_b", "n", "own", "cut")]) for side in ("left", "right"))
    longer = F.greatest("left_n", "right_n")
    met = left.filter("left_in_a").join(right.filter("right_in_b"), ["token", "low", "high"]).filter(
        (F.col("left_value") < F.col("right_value")) & (longer - F.least("left_n", "right_n") <= edits(longer))
        & (F.least("left_cut", "right_cut") == F.col("low")) & (F.greatest("left_cut", "right_cut") == F.col("high"))
        & (F.element_at(F.array_intersect("left_own", "right_own"), 1) == F.col("token"))
    )
    far = F.levenshtein("left_value", "right_value") / longer
    return met.select("left_value", "right_value", F.round(1 - far, 6).alias("similarity")).filter(F.col("similarity") >= threshold)


def detect_errors(df: DataFrame, rules: dict[str, str], keys: list[str]) -> DataFrame:
    """A row for each rule that a row violates; one scan."""
    broken = F.filter(F.array(*[F.when(F.coalesce(F.expr(e), F.lit(True)), F.lit(None).cast("string")).otherwise(F.lit(n)) for n, e in rules.items()]), lambda x: x.isNotNull())
    return df.select(*keys, F.explode(broken).alias("rule"))


def semantic_filter(df: DataFrame, column: str, decide, out: str = "decision") -> DataFrame:
    """A decision by an injected function, once for each distinct text."""
    def run(texts: pd.Series) -> pd.Series:
        return pd.Series([bool(decide(t)) for t in texts])

    known = df.select(F.col(column).alias("_text")).distinct().withColumn(out, F.pandas_udf(run, "boolean")("_text"))
    return df.join(known, df[column].eqNullSafe(known["_text"]), "left").drop("_text")
