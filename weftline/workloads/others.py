"""Churn from several sources, text quality with classifiers, and discovery by many small profiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.encoders import char_ngrams
from ..plans.pipeline import Pipeline, PipelineBatch, choose, expand_variants

CUTOFF = "2001-02-01"


def churn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A row a customer: demographics, purchases before the cutoff, usage, text, and the label."""
    t = {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in ("customer", "nation", "region", "orders", "events", "conversations")}
    cutoff = F.expr(f"TIMESTAMP_NTZ '{CUTOFF}'")
    money = F.col("o_totalprice").cast("decimal(18,2)")
    bought = t["orders"].groupBy(F.col("o_custkey").alias("c_custkey")).agg(
        F.count_if(F.col("o_orderdate") < cutoff).alias("n_orders"),
        F.coalesce(F.sum(F.when(F.col("o_orderdate") < cutoff, money)), F.lit(0)).cast("double").alias("spent"),
        F.datediff(F.lit(CUTOFF).cast("date"), F.max(F.when(F.col("o_orderdate") < cutoff, F.col("o_orderdate")))).cast("bigint").alias("recency"),
        (F.max("o_orderdate") < cutoff).cast("int").alias("churned"),
    )
    used = t["events"].groupBy(F.col("user_id").alias("c_custkey")).agg(
        F.count("*").alias("n_events"), F.count_if(F.col("event_type") == "purchase").alias("n_purchases"),
        F.round(F.avg(F.from_json("props", "k int")["k"]), 6).alias("mean_k"),
    )
    said = t["conversations"].groupBy(F.col("conv_id").alias("c_custkey")).agg(F.count("*").alias("n_turns"), F.count_if(F.col("role") == "user").alias("n_user_turns"))
    base = t["customer"].join(t["nation"], F.col("n_nationkey") == F.col("c_nationkey")).join(t["region"], F.col("r_regionkey") == F.col("n_regionkey"))
    return base.join(bought, "c_custkey", "left").join(used, "c_custkey", "left").join(said, "c_custkey", "left").select(
        "c_custkey", "n_name", "r_name", "c_mktsegment", "c_acctbal", "n_orders", "spent", "recency", "n_events", "n_purchases", "mean_k", "n_turns", "n_user_turns", "churned"
    )


CHURN_SQL = f"""
WITH b AS (SELECT o_custkey AS c_custkey, CAST(count(*) FILTER (WHERE o_orderdate < TIMESTAMP '{CUTOFF}') AS BIGINT) AS n_orders,
 CAST(coalesce(sum(CAST(o_totalprice AS DECIMAL(18,2))) FILTER (WHERE o_orderdate < TIMESTAMP '{CUTOFF}'), 0) AS DOUBLE) AS spent,
 date_diff('day', CAST(max(o_orderdate) FILTER (WHERE o_orderdate < TIMESTAMP '{CUTOFF}') AS DATE), DATE '{CUTOFF}') AS recency,
 CAST(max(o_orderdate) < TIMESTAMP '{CUTOFF}' AS INT) AS churned FROM orders GROUP BY 1),
u AS (SELECT user_id AS c_custkey, CAST(count(*) AS BIGINT) AS n_events, CAST(count(*) FILTER (WHERE event_type = 'purchase') AS BIGINT) AS n_purchases,
 round(avg(CAST(json_extract(props, '$.k') AS INT)), 6) AS mean_k FROM events GROUP BY 1),
s AS (SELECT conv_id AS c_custkey, CAST(count(*) AS BIGINT) AS n_turns, CAST(count(*) FILTER (WHERE role = 'user') AS BIGINT) AS n_user_turns FROM conversations GROUP BY 1)
SELECT c_custkey, n_name, r_name, c_mktsegment, c_acctbal, n_orders, spent, recency, n_events, n_purchases, mean_k, n_turns, n_user_turns, churned
FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey
LEFT JOIN b USING (c_custkey) LEFT JOIN u USING (c_custkey) LEFT JOIN s USING (c_custkey)
"""


def text_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labelled documents with simple features and counts of three-character runs."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in ("documents", "labels"))
    size = F.length("text")
    return docs.join(labels, "doc_id").select(
        "doc_id", "lang", "source", "quality", "toxic", "n_chars",
        F.greatest(size - 2, F.lit(0)).cast("bigint").alias("n_grams"),
        F.size(F.array_distinct(char_ngrams(F.lower("text"), 3))).cast("bigint").alias("n_distinct_grams"),
        F.round(F.length(F.regexp_replace("text", "[^#*$%&|<>]", "")) / F.col("n_chars"), 6).alias("symbol_share"),
    )


TEXT_SQL = """
WITH d AS (SELECT *, lower(text) AS t FROM documents JOIN labels USING (doc_id)),
g AS (SELECT *, CASE WHEN length(t) >= 3 THEN [t[i:i+2] FOR i IN range(1, length(t) - 1)] ELSE [] END AS grams FROM d)
SELECT doc_id, lang, source, quality, toxic, n_chars, CAST(len(grams) AS BIGINT) AS n_grams, CAST(len(list_distinct(grams)) AS BIGINT) AS n_distinct_grams,
 round(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) / n_chars, 6) AS symbol_share FROM g
"""


def churn_model_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers with a label, split by key."""
    told = churn(spark, sf_dir).filter("churned is not null")
    return told.withColumn("bucket", (F.col("c_custkey") * 7919 % 10).cast("int"))


def text_model_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    told = text_features(spark, sf_dir)
    ratio = F.col("n_distinct_grams") / F.greatest(F.col("n_grams"), F.lit(1))
    return told.withColumns({"bucket": (F.col("doc_id") * 7919 % 10).cast("int"), "gram_ratio": ratio})


#: Sources that are views: how they are made and the tables behind them.
VIEWS = {
    "churn": (churn_model_rows, ("customer", "nation", "region", "orders", "events", "conversations")),
    "labelled_texts": (text_model_rows, ("documents", "labels")),
}


def model_batch(source: str, target: str, preps: dict[str, dict], models: dict[str, dict], metric: str = "auc") -> PipelineBatch:
    train, valid = "bucket < 7", "bucket >= 7"
    prep = choose("prep", {k: (lambda p, v=v: p.prepare(v, train, target)) for k, v in preps.items()})
    model = choose("model", {k: (lambda p, v=v: p.model(v, train, target).score(metric, valid, target)) for k, v in models.items()})
    return PipelineBatch(tuple(expand_variants(Pipeline.read(source), [prep, model])))


CLASSIFIERS = {"logistic": {"kind": "logistic", "alpha": 0.1}, "perceptron": {"kind": "perceptron", "hidden": 3, "epochs": 30}}


def churn_batch() -> PipelineBatch:
    """Two preparations by two classifiers of whether a customer left."""
    numbers = {"kind": "numeric", "cols": ["c_acctbal", "n_orders", "spent", "n_events", "n_turns"], "impute": "const", "constant": 0}
    carry = ["churned", "bucket"]
    preps = {"numbers": {"encoders": [numbers], "carry": carry}, "all": {"encoders": [numbers, {"kind": "onehot", "cols": ["c_mktsegment", "r_name"]}], "carry": carry}}
    return model_batch("churn", "churned", preps, CLASSIFIERS)


def text_batch(target: str = "quality") -> PipelineBatch:
    """Two preparations by two classifiers of labelled documents."""
    numbers = {"kind": "numeric", "cols": ["n_chars", "n_distinct_grams", "gram_ratio", "symbol_share"]}
    carry = [target, "bucket"]
    preps = {"numbers": {"encoders": [numbers], "carry": carry}, "all": {"encoders": [numbers, {"kind": "onehot", "cols": ["lang", "source"]}], "carry": carry}}
    return model_batch("labelled_texts", target, preps, CLASSIFIERS)


#: Light profiling scripts, as an agent writes them one by one: name to (table, aggregate as SQL for both engines).
def discovery_scripts() -> dict[str, tuple[str, str]]:
    numbers = {
        "lineitem": ("l_quantity", "l_extendedprice", "l_discount", "l_tax"), "orders": ("o_totalprice",), "part": ("p_size", "p_retailprice"),
        "customer": ("c_acctbal",), "supplier": ("s_acctbal",), "events": ("value",),
    }
    kinds = {"min": "min({}) + 0", "max": "max({})", "missing": "count(*) - count({})", "distinct": "count(DISTINCT {})"}
    return {f"{t}/{c}/{k}": (t, f"CAST({e.format(c)} AS DOUBLE)") for t, cs in numbers.items() for c in cs for k, e in kinds.items()}


def discovery(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All scripts as one fused batch: a scan a table, however many scripts read it."""
    by_table: dict[str, dict[str, str]] = {}
    for name, (table, told) in discovery_scripts().items():
        by_table.setdefault(table, {})[name] = told
    out = None
    for table, scripts in sorted(by_table.items()):
        row = spark.read.parquet(f"{sf_dir}/{table}.parquet").agg(*[F.expr(e).alias(f"r{k}") for k, e in enumerate(scripts.values())])
        rows = F.array(*[F.struct(F.lit(n).alias("script"), F.col(f"r{k}").alias("value")) for k, n in enumerate(scripts)])
        part = row.select(F.explode(rows).alias("r")).select("r.*")
        out = part if out is None else out.unionAll(part)
    return out


DISCOVERY_SQL = " UNION ALL ".join(f"SELECT '{n}' AS script, {e} AS value FROM {t}" for n, (t, e) in discovery_scripts().items())
