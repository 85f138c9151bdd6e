"""The listing view: priced items that stand in for housing data, and its pipelines."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.pipeline import Pipeline, PipelineBatch, choose, expand_variants

#: Columns as SQL that Spark and DuckDB read alike.
COLUMNS = {
    "l_orderkey": "l_orderkey", "l_linenumber": "l_linenumber", "l_partkey": "l_partkey", "l_suppkey": "l_suppkey",
    "size_m": "CASE WHEN (l_partkey*13+l_suppkey*7)%17=0 THEN NULL ELSE p_size END",
    "quantity_m": "CASE WHEN (l_orderkey+l_linenumber)%19=0 THEN NULL ELSE l_quantity END",
    "segment_raw": "CASE WHEN l_orderkey%23=0 THEN ' N/A ' WHEN l_orderkey%29=0 THEN '' ELSE c_mktsegment END",
    "p_type": "p_type", "p_brand": "p_brand", "l_returnflag": "l_returnflag", "p_name": "p_name",
    "n_name": "n_name", "s_name": "s_name", "l_shipdate": "l_shipdate", "p_retailprice": "p_retailprice",
    "price": """CAST(round(p_retailprice*10) AS BIGINT)*(50+p_size) + 7000*CAST(substr(p_brand,7) AS INT) + 20000*n_regionkey
 + CASE p_type WHEN 'ECONOMY' THEN 0 WHEN 'STANDARD' THEN 40000 WHEN 'MEDIUM' THEN 80000 WHEN 'LARGE' THEN 120000 ELSE 160000 END
 + ((l_orderkey*7919 + l_partkey*104729 + l_suppkey*1299709 + l_linenumber*31) % 100001) - 50000""",
    "bucket": "CAST((l_orderkey*31+l_partkey*17+l_suppkey*7+l_linenumber)%10 AS INT)",
    "fold": "CAST((l_orderkey*31+l_partkey*17+l_suppkey*7+l_linenumber)%10 AS INT) % 4",
}
LISTING_SQL = "SELECT " + ", ".join(f"{e} AS {c}" for c, e in COLUMNS.items()) + """
FROM lineitem JOIN part ON p_partkey = l_partkey JOIN orders ON o_orderkey = l_orderkey
JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN supplier ON s_suppkey = l_suppkey"""


def listing(spark: SparkSession, sf_dir: str, columns: list[str] | None = None) -> DataFrame:
    """Catalyst prunes columns and picks the joins; dimensions are broadcast where they are small."""
    t = {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in ("lineitem", "part", "orders", "customer", "nation", "supplier")}
    cores = spark.sparkContext.defaultParallelism
    if t["lineitem"].rdd.getNumPartitions() < cores:  # few row groups would leave cores idle in every pass that follows
        t["lineitem"] = t["lineitem"].repartition(cores)
    joined = (
        t["lineitem"].join(t["part"], F.col("p_partkey") == F.col("l_partkey")).join(t["orders"], F.col("o_orderkey") == F.col("l_orderkey"))
        .join(t["customer"], F.col("c_custkey") == F.col("o_custkey")).join(t["nation"], F.col("n_nationkey") == F.col("c_nationkey"))
        .join(t["supplier"], F.col("s_suppkey") == F.col("l_suppkey"))
    )
    return joined.select(*[F.expr(COLUMNS[c]).alias(c) for c in columns or COLUMNS])


TRAIN, VALID, TARGET = "bucket < 8", "bucket = 8", "price"
CARRY = ["price", "bucket", "fold"]
NUMBERS = ["size_m", "quantity_m", "p_retailprice"]

PREP_A = {"encoders": [
    {"kind": "numeric", "cols": NUMBERS, "impute": "mean"},
    {"kind": "text", "cols": ["p_name"], "n_components": 4},
    {"kind": "target", "cols": ["s_name", "n_name"], "fold": "fold", "smoothing": 20.0},
], "carry": CARRY}
PREP_B = {"encoders": [
    {"kind": "numeric", "cols": NUMBERS, "impute": "median"},
    {"kind": "onehot", "cols": ["p_type", "p_brand", "l_returnflag", "segment_raw", "n_name"]},
    {"kind": "text", "cols": ["p_name", "s_name"], "n_components": 3},
], "carry": CARRY}
MODELS = {
    "ridge": {"kind": "ridge", "alpha": 1.0},
    "elastic_net": {"kind": "elastic_net", "alpha": 0.01, "rho": 0.5},
    "trees_level": {"kind": "trees", "growth": "level", "trees": 6, "depth": 3},
    "trees_leaf": {"kind": "trees", "growth": "leaf", "trees": 6, "leaves": 8},
}


def batch(preps: dict[str, dict], models: dict[str, dict], stage: str = "explore") -> PipelineBatch:
    prep = choose("prep", {k: (lambda p, v=v: p.prepare(v, TRAIN, TARGET)) for k, v in preps.items()})
    model = choose("model", {k: (lambda p, v=v: p.model(v, TRAIN, TARGET).score("rmse", VALID, TARGET)) for k, v in models.items()})
    return PipelineBatch(tuple(expand_variants(Pipeline.read("listing"), [prep, model])), stage)


def iteration_one() -> PipelineBatch:
    """Two preparations by four models."""
    return batch({"a": PREP_A, "b": PREP_B}, MODELS)


def iteration_two(winner: str) -> PipelineBatch:
    """Hyper-parameters of the winning preparation and model."""
    prep, model = winner.split("/")
    grids = {
        "ridge": [MODELS["ridge"] | {"alpha": a} for a in (0.01, 0.1, 1.0, 10.0, 100.0, 1000.0)],
        "elastic_net": [MODELS["elastic_net"] | {"alpha": a, "rho": r} for a in (0.001, 0.01, 0.1) for r in (0.2, 0.8)],
        "trees_level": [MODELS["trees_level"] | {"depth": d, "eta": e} for d in (2, 3, 4) for e in (0.2, 0.5)],
        "trees_leaf": [MODELS["trees_leaf"] | {"leaves": n, "eta": e} for n in (4, 8, 12) for e in (0.2, 0.5)],
    }
    return batch({prep: {"a": PREP_A, "b": PREP_B}[prep]}, {f"{model}-{k}": m for k, m in enumerate(grids[model])}, "exploit")


SCALED = {"encoders": [{"kind": "numeric", "cols": NUMBERS, "impute": "mean"}], "carry": CARRY}
ONEHOT = {"encoders": [*SCALED["encoders"], {"kind": "onehot", "cols": ["p_type", "p_brand"]}], "carry": CARRY}


def fused_four() -> PipelineBatch:
    """The smallest fused batch: two preparations by ridge and elastic net."""
    return batch({"scaled": SCALED, "onehot": ONEHOT}, {k: MODELS[k] for k in ("ridge", "elastic_net")})


def code_example(alphas: tuple[float, ...] = (0.1, 1.0, 10.0)) -> Pipeline:
    """Read, encode automatically, search a grid with cross-validation."""
    grid = [{"kind": "ridge", "alpha": a} for a in alphas]
    columns = ["size_m", "quantity_m", "p_retailprice", "p_type", "p_brand", "l_returnflag", "segment_raw", "p_name"]
    read = Pipeline.read("listing").project(*columns, *CARRY)
    return read.auto_prepare(TRAIN, TARGET, columns=columns, carry=CARRY).grid_search(grid, TRAIN, TARGET).named("code_example")


def infeasible() -> PipelineBatch:
    """A batch with a one-hot encoding beyond its bound and a function that fails."""
    wide = {"encoders": [{"kind": "onehot", "cols": ["s_name"], "max_categories": 5}], "carry": CARRY}

    def broken(df: DataFrame) -> DataFrame:
        raise ValueError("a step that an agent wrote wrongly")

    good = batch({"scaled": SCALED}, {"ridge": MODELS["ridge"]}).pipelines
    bad = batch({"wide": wide}, {"ridge": MODELS["ridge"]}).pipelines
    failing = Pipeline.read("listing").call(broken).prepare(SCALED, TRAIN, TARGET).model(MODELS["ridge"], TRAIN, TARGET).score("rmse", VALID, TARGET)
    return PipelineBatch((*good, *bad, failing.named("failing/ridge")))
