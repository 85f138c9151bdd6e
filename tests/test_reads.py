"""Queries on plans and measures do their job on rows of a given table, which Spark's tasks read."""

import pytest

from weftline.queries import QUERIES
from weftline.runtime import metadata


def read_records(spark):
    store, gateway = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._gateway
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    stages = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
    return sum(stages.apply(i).inputRecords() for i in range(stages.size()))


@pytest.mark.parametrize(
    "name, table", [("b3_cse_prep_once", "lineitem"), ("d10_map_udf_shape", "supplier"), ("d2_binding", "part"), ("d9_replan", "part"), ("f3_no_oversubscription", "lineitem"), ("g1_fingerprint", "part"), ("h3_low_fidelity", "part"), ("m6_changed_lines", "conversations"), ("sql_cte", "orders")]
)
def test_tasks_read_the_table(spark, tiny, name, table):
    for source in ("listing", "part", "supplier"):  # counts of footers, kept from here on, read no rows
        metadata.source_rows(spark, tiny, source)
    rows, before = spark.read.parquet(f"{tiny}/{table}.parquet").count(), read_records(spark)
    assert QUERIES[name](spark, tiny).collect()
    assert read_records(spark) - before >= rows
