"""The metadata pass: rows, columns and types of every node of a plan before it runs."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import SparkSession

from ..plans.ir import Dag
from ..plans.select import Meta, propagate
from ..workloads import others
from ..workloads.listing import COLUMNS

#: Rows by path and source: counted from footers, once.
_ROWS: dict[tuple, int] = {}


def source_rows(spark: SparkSession, sf_dir: str, source: str) -> int:
    """Rows of a source; a count without columns reads the files' footers alone."""
    table = "lineitem" if source == "listing" else others.VIEWS[source][1][0] if source in others.VIEWS else source
    key = (spark.sparkContext.applicationId, sf_dir, table)
    if key not in _ROWS:
        _ROWS[key] = spark.read.parquet(f"{sf_dir}/{table}.parquet").count()
    return _ROWS[key]


def source_types(spark: SparkSession, sf_dir: str, source: str) -> dict[str, str]:
    if source == "listing":
        return dict.fromkeys(COLUMNS, "")
    if source in others.VIEWS:
        return dict(others.VIEWS[source][0](spark, sf_dir).dtypes)
    return dict(spark.read.parquet(f"{sf_dir}/{source}.parquet").dtypes)


def collect_metadata(dag: Dag, spark: SparkSession, sf_dir: str, mode: str = "footer") -> dict[str, Meta]:
    """Meta by node key; sources by their footers, other nodes by what their operators do.

    With ``mode`` sample, filters are estimated on a thousandth of the rows.
    """
    sources = {}
    for n in replace(dag, shared=True).nodes():
        if n.op == "READ" and n.params["source"] not in sources:
            source = n.params["source"]
            sources[source] = Meta(float(source_rows(spark, sf_dir, source)), float(len(source_types(spark, sf_dir, source))))
    return propagate(dag, sources)


def described(dag: Dag, spark: SparkSession, sf_dir: str) -> list[tuple]:
    """(operator, kind, source, rows, columns) of every node."""
    metas = collect_metadata(dag, spark, sf_dir)
    kinds = {"READ": "source", "FILTER": "selection", "PROJECT": "projection", "ASSIGN": "map", "UDF": "function", "FIT_PREP": "estimator", "FIT_MODEL": "estimator", "APPLY_PREP": "transformer", "APPLY_MODEL": "transformer"}
    return [(n.op, kinds.get(n.op, "operator"), n.params.get("source"), int(metas[n.key].rows), int(metas[n.key].cols)) for n in replace(dag, shared=True).nodes()]
