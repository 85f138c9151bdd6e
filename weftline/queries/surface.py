"""Queries over the relational surface around the methods."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import relational as rel
from ..sources.files import round_trip
from .base import Tables, query

_NATION = "SELECT n_nationkey, n_name, n_regionkey FROM nation"


@query("src_parquet", _NATION)
def _(t: Tables) -> DataFrame:
    return round_trip(t.nation, "parquet")


@query("src_csv_roundtrip", _NATION)
def _(t):
    return round_trip(t.nation, "csv", header="true")


@query("src_json_roundtrip", _NATION)
def _(t):
    return round_trip(t.nation, "json")


@query("src_orc_roundtrip", _NATION)
def _(t):
    return round_trip(t.nation, "orc")


@query("src_partitioned", "SELECT n_nationkey, n_name, n_regionkey FROM nation WHERE n_regionkey = 2")
def _(t):
    return round_trip(t.nation, "parquet", ["n_regionkey"]).filter("n_regionkey = 2")


@query("prj_computed", "SELECT l_orderkey, l_linenumber, l_suppkey, l_extendedprice * (1 - l_discount) AS net, l_quantity * 2 AS twice FROM lineitem")
def _(t):
    return t.lineitem.select("l_orderkey", "l_linenumber", "l_suppkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("net"), (F.col("l_quantity") * 2).alias("twice"))


@query("prj_struct", "SELECT c_custkey, c_name AS name, c_mktsegment AS segment FROM customer")
def _(t):
    return t.customer.select("c_custkey", F.struct(F.col("c_name").alias("name"), F.col("c_mktsegment").alias("segment")).alias("who")).select("c_custkey", "who.*")


@query("flt_range", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_shipdate >= TIMESTAMP '1998-01-01'")
def _(t):
    return t.lineitem.filter(F.col("l_quantity").between(10, 20) & (F.col("l_shipdate") >= F.expr("TIMESTAMP_NTZ '1998-01-01'"))).select("l_orderkey", "l_quantity")


@query("flt_in", "SELECT p_partkey, p_type FROM part WHERE p_type IN ('SMALL', 'LARGE') OR p_brand IN (SELECT p_brand FROM part WHERE p_size = 1)")
def _(t):
    few = t.part.filter("p_size = 1").select(F.col("p_brand").alias("b")).distinct()
    flagged = t.part.join(few.withColumn("hit", F.lit(True)), F.col("p_brand") == F.col("b"), "left")
    return flagged.filter(F.col("p_type").isin("SMALL", "LARGE") | F.col("hit")).select("p_partkey", "p_type")


@query("flt_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_name, '^[a-m]')")
def _(t):
    return t.part.filter(F.col("p_name").like("%a%") & F.col("p_name").rlike("^[a-m]")).select("p_partkey", "p_name")


@query("flt_null", "SELECT o_orderkey FROM orders WHERE nullif(o_orderstatus, 'F') IS NULL")
def _(t):
    return t.orders.filter(F.nullif("o_orderstatus", F.lit("F")).isNull()).select("o_orderkey")


_RICH = "(SELECT * FROM customer WHERE c_acctbal > 5000)"
for _how, _sql in {
    "inner": f"SELECT o_orderkey, c_name FROM orders JOIN {_RICH} ON c_custkey = o_custkey",
    "left": f"SELECT o_orderkey, c_name FROM orders LEFT JOIN {_RICH} ON c_custkey = o_custkey",
    "right": "SELECT o_orderkey, c_name FROM (SELECT * FROM orders WHERE o_totalprice > 300000) RIGHT JOIN customer ON c_custkey = o_custkey",
    "full": f"SELECT o_orderkey, c_name FROM (SELECT * FROM orders WHERE o_totalprice > 300000) FULL JOIN {_RICH} ON c_custkey = o_custkey",
}.items():

    @query(f"join_{_how}", _sql)
    def _(t, how=_how):
        rich = t.customer.filter("c_acctbal > 5000") if how != "right" else t.customer
        big = t.orders.filter("o_totalprice > 300000") if how in ("right", "full") else t.orders
        return big.join(rich, F.col("c_custkey") == F.col("o_custkey"), how).select("o_orderkey", "c_name")


@query("join_cross", "SELECT r_name, n_name FROM region, nation")
def _(t):
    # two tables of fixed size: 5 by 25 rows
    return t.region.crossJoin(t.nation).select("r_name", "n_name")


@query("join_semi", f"SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM {_RICH})")
def _(t):
    return t.orders.join(t.customer.filter("c_acctbal > 5000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("o_orderkey")


@query("join_anti", f"SELECT o_orderkey FROM orders WHERE o_custkey NOT IN (SELECT c_custkey FROM {_RICH})")
def _(t):
    return t.orders.join(t.customer.filter("c_acctbal > 5000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("o_orderkey")


for _name, _hint in {"bc": "broadcast", "sh": "shuffle_hash", "smj": "merge"}.items():

    @query(f"join_hint_{_name}", "SELECT n_name, CAST(count(*) AS BIGINT) AS n FROM supplier JOIN nation ON n_nationkey = s_nationkey GROUP BY n_name")
    def _(t, hint=_hint):
        return t.supplier.join(t.nation.hint(hint), F.col("n_nationkey") == F.col("s_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("join_range", "SELECT p_partkey, k FROM part JOIN (SELECT unnest(range(0, 20)) AS k) ON p_retailprice >= 900 + k * 5 AND p_retailprice < 900 + k * 5 + 7")
def _(t):
    bands = t.spark.range(20).select(F.col("id").alias("k"), (900.0 + F.col("id") * 5).alias("low"), (907.0 + F.col("id") * 5).alias("high"))
    return rel.range_join(t.part, bands, "p_retailprice", "low", "high", 5.0).select("p_partkey", "k")


@query("join_interval", """SELECT a.event_id AS first_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id
 AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 3600 SECONDS""")
def _(t):
    a = t.events.select("user_id", F.col("event_id").alias("first_id"), F.col("ts").alias("first_ts"))
    b = t.events.select("user_id", F.col("event_id").alias("next_id"), F.col("ts").alias("next_ts"))
    return rel.interval_join(a, b, "user_id", "first_ts", "next_ts", 3600).select("first_id", "next_id")


@query("join_asof", """SELECT event_id, (SELECT value FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'purchase'
 AND b.ts <= a.ts ORDER BY b.ts DESC, b.event_id DESC LIMIT 1) AS last_purchase FROM events a WHERE event_type = 'click'""")
def _(t):
    return rel.asof_join(t.events.filter("event_type = 'click'"), t.events.filter("event_type = 'purchase'"), "user_id", "ts", "value", "last_purchase", "event_id").select("event_id", "last_purchase")


@query("join_salted", "SELECT c_mktsegment, CAST(count(*) AS BIGINT) AS n FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1")
def _(t):
    orders = t.orders.select(F.col("o_custkey").alias("c_custkey"), "o_orderkey")
    return rel.salted_join(orders, t.customer.select("c_custkey", "c_mktsegment"), "c_custkey", 4, "o_orderkey").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


_CENTS = "CAST(l_extendedprice AS DECIMAL(18,2))"


@query("agg_basic", f"SELECT l_returnflag, CAST(count(*) AS BIGINT) AS n, CAST(sum({_CENTS}) AS DOUBLE) AS total, min(l_quantity) AS low, max(l_quantity) AS high, round(avg(l_discount), 6) AS disc FROM lineitem GROUP BY 1")
def _(t):
    return t.lineitem.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum(F.expr(_CENTS)).cast("double").alias("total"), F.min("l_quantity").alias("low"), F.max("l_quantity").alias("high"), F.round(F.avg("l_discount"), 6).alias("disc"))


@query("agg_stats", "SELECT l_returnflag, round(stddev_pop(l_quantity), 5) AS sd, round(var_pop(l_quantity), 4) AS v, round(corr(l_quantity, l_extendedprice), 5) AS r, round(regr_slope(l_extendedprice, l_quantity), 3) AS slope, quantile_cont(l_quantity, 0.5) AS med FROM lineitem GROUP BY 1")
def _(t):
    return t.lineitem.groupBy("l_returnflag").agg(F.round(F.stddev_pop("l_quantity"), 5).alias("sd"), F.round(F.var_pop("l_quantity"), 4).alias("v"), F.round(F.corr("l_quantity", "l_extendedprice"), 5).alias("r"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 3).alias("slope"), F.percentile("l_quantity", 0.5).alias("med"))


@query("agg_distinct", "SELECT l_returnflag, CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts, CAST(count(DISTINCT l_suppkey) AS BIGINT) AS supps FROM lineitem GROUP BY 1")
def _(t):
    return t.lineitem.groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("supps"))


@query("agg_filter", "SELECT l_linestatus, CAST(count(*) FILTER (WHERE l_quantity > 25) AS BIGINT) AS many, max(l_tax) FILTER (WHERE l_discount = 0) AS tax FROM lineitem GROUP BY 1")
def _(t):
    return t.lineitem.groupBy("l_linestatus").agg(F.count_if(F.col("l_quantity") > 25).alias("many"), F.max(F.when(F.col("l_discount") == 0, F.col("l_tax"))).alias("tax"))


_GROUPED = "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY "


@query("agg_rollup", _GROUPED + "ROLLUP (l_returnflag, l_linestatus)")
def _(t):
    return t.lineitem.rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("agg_cube", _GROUPED + "CUBE (l_returnflag, l_linestatus)")
def _(t):
    return t.lineitem.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("agg_gsets", _GROUPED + "GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def _(t):
    a, b = F.col("l_returnflag"), F.col("l_linestatus")
    return t.lineitem.groupingSets([[a], [b], []], a, b).agg(F.count("*").alias("n"))


@query("agg_pivot", "SELECT o_orderpriority, CAST(count(*) FILTER (WHERE o_orderstatus = 'F') AS BIGINT) AS f, CAST(count(*) FILTER (WHERE o_orderstatus = 'O') AS BIGINT) AS o FROM orders GROUP BY 1")
def _(t):
    return t.orders.groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1))).select("o_orderpriority", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@query("agg_unpivot", "SELECT l_orderkey, l_linenumber, l_suppkey, 'l_discount' AS what, l_discount AS v FROM lineitem UNION ALL SELECT l_orderkey, l_linenumber, l_suppkey, 'l_tax', l_tax FROM lineitem")
def _(t):
    return t.lineitem.select("l_orderkey", "l_linenumber", "l_suppkey", "l_discount", "l_tax").unpivot(["l_orderkey", "l_linenumber", "l_suppkey"], ["l_discount", "l_tax"], "what", "v")


@query("agg_having", "SELECT o_custkey, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1 HAVING count(*) >= 12")
def _(t):
    return t.orders.groupBy("o_custkey").agg(F.count("*").alias("n")).filter("n >= 12")


@query("agg_sketches", "SELECT event_type, true AS users_close, true AS users_hll_close, true AS median_close, true AS median_kll_close FROM events GROUP BY 1")
def _(t):
    close = lambda a, b: F.abs(F.col(a) - F.col(b)) <= 0.08 * F.abs(F.col(b)) + 1e-9
    told = t.events.groupBy("event_type").agg(
        F.approx_count_distinct("user_id", 0.02).alias("users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users_hll"),
        F.percentile_approx("value", 0.5, 10_000).alias("median"), F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("value"), F.lit(0.5)).alias("median_kll"),
        F.count_distinct("user_id").alias("n"), F.percentile("value", 0.5).alias("m"),
    )
    return told.select("event_type", close("users", "n").alias("users_close"), close("users_hll", "n").alias("users_hll_close"), close("median", "m").alias("median_close"), close("median_kll", "m").alias("median_kll_close"))


def _per():
    """Made when asked for: a window needs a session."""
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


_OVER = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"


@query("win_rank", f"SELECT o_orderkey, row_number() {_OVER}) AS rn, ntile(3) {_OVER}) AS third, round(percent_rank() {_OVER}), 6) AS pr, round(cume_dist() {_OVER}), 6) AS cd FROM orders")
def _(t):
    return t.orders.select("o_orderkey", F.row_number().over(_per()).cast("bigint").alias("rn"), F.ntile(3).over(_per()).cast("bigint").alias("third"), F.round(F.percent_rank().over(_per()), 6).alias("pr"), F.round(F.cume_dist().over(_per()), 6).alias("cd"))


@query("win_lag", f"SELECT o_orderkey, lag(o_orderkey) {_OVER}) AS before, lead(o_orderkey) {_OVER}) AS after, first_value(o_orderkey) {_OVER}) AS first FROM orders")
def _(t):
    return t.orders.select("o_orderkey", F.lag("o_orderkey").over(_per()).alias("before"), F.lead("o_orderkey").over(_per()).alias("after"), F.first("o_orderkey").over(_per()).alias("first"))


@query("win_running", f"SELECT o_orderkey, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) {_OVER} ROWS UNBOUNDED PRECEDING) AS DOUBLE) AS running FROM orders")
def _(t):
    w = _per().rowsBetween(Window.unboundedPreceding, 0)
    return t.orders.select("o_orderkey", F.sum(F.col("o_totalprice").cast("decimal(18,2)")).over(w).cast("double").alias("running"))


@query("win_moving", f"SELECT o_orderkey, max(o_totalprice) {_OVER} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS moving FROM orders")
def _(t):
    return t.orders.select("o_orderkey", F.max("o_totalprice").over(_per().rowsBetween(-2, 0)).alias("moving"))


@query("win_range", "SELECT p_partkey, CAST(count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND CURRENT ROW) AS BIGINT) AS near FROM part")
def _(t):
    return t.part.select("p_partkey", F.count("*").over(Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 0)).alias("near"))


@query("win_sessionize", """WITH d AS (SELECT *, CASE WHEN ts > lag(ts) OVER w + INTERVAL 7200 SECONDS OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events
 WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM d)
 SELECT user_id, CAST(session AS BIGINT) AS session, CAST(count(*) AS BIGINT) AS n FROM s GROUP BY 1, 2""")
def _(t):
    return rel.sessionize(t.events, "user_id", "ts", "event_id", 7200).groupBy("user_id", "session").agg(F.count("*").alias("n"))


@query("srt_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def _(t):
    return t.orders.select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("srt_topk_group", "SELECT o_orderkey, o_orderpriority FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def _(t):
    return rel.top_k_per_group(t.orders, "o_orderpriority", [F.desc("o_totalprice"), F.col("o_orderkey")], 3).select("o_orderkey", "o_orderpriority")


@query("srt_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 25")
def _(t):
    return t.orders.select("o_orderkey").orderBy("o_orderkey").offset(25).limit(10)


_C, _S = "SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 9000", "SELECT s_nationkey AS k FROM supplier"


def _sides(t):
    return t.customer.filter("c_acctbal > 9000").select(F.col("c_nationkey").alias("k")), t.supplier.select(F.col("s_nationkey").alias("k"))


@query("set_union", f"{_C} UNION {_S}")
def _(t):
    a, b = _sides(t)
    return a.unionByName(b).distinct()


@query("set_intersect", f"{_C} INTERSECT ALL {_S}")
def _(t):
    a, b = _sides(t)
    return a.intersectAll(b)


@query("set_except", f"{_C} EXCEPT ALL {_S}")
def _(t):
    a, b = _sides(t)
    return a.exceptAll(b)


@query("fn_string", "SELECT p_partkey, upper(p_name) AS u, length(p_name) AS n, substr(p_name, 2, 3) AS s, concat_ws('-', p_brand, p_type) AS c, lpad(CAST(p_size AS VARCHAR), 4, '0') AS l, replace(p_name, 'a', 'o') AS r, levenshtein(p_name, p_type) AS d FROM part")
def _(t):
    return t.part.select("p_partkey", F.upper("p_name").alias("u"), F.length("p_name").cast("bigint").alias("n"), F.substring("p_name", 2, 3).alias("s"), F.concat_ws("-", "p_brand", "p_type").alias("c"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("l"), F.replace("p_name", F.lit("a"), F.lit("o")).alias("r"), F.levenshtein("p_name", "p_type").cast("bigint").alias("d"))


@query("fn_regex", "SELECT page_id, regexp_extract(url, '^(https?)://', 1) AS scheme, regexp_replace(url, '[0-9]+', '#', 'g') AS masked, split_part(url, '/', 3) AS host FROM pages")
def _(t):
    return t.pages.select("page_id", F.regexp_extract("url", "^(https?)://", 1).alias("scheme"), F.regexp_replace("url", "[0-9]+", "#").alias("masked"), F.split_part("url", F.lit("/"), F.lit(3)).alias("host"))


@query("fn_hash", "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents")
def _(t):
    return t.documents.select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"))


@query("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_trunc('month', o_orderdate) AS t, CAST(last_day(o_orderdate) AS VARCHAR) AS l, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS d FROM orders")
def _(t):
    d = F.col("o_orderdate")
    return t.orders.select("o_orderkey", F.year(d).cast("bigint").alias("y"), F.month(d).cast("bigint").alias("m"), F.date_trunc("month", d).cast("timestamp_ntz").alias("t"), F.last_day(d).cast("string").alias("l"), F.datediff(d, F.lit("1995-01-01").cast("date")).cast("bigint").alias("d"))


@query("fn_interval", "SELECT o_orderkey, o_orderdate + INTERVAL 90 DAYS AS later, date_diff('day', o_orderdate, TIMESTAMP '2001-02-01') AS age FROM orders")
def _(t):
    return t.orders.select("o_orderkey", (F.col("o_orderdate") + F.expr("INTERVAL 90 DAYS")).alias("later"), F.datediff(F.expr("DATE '2001-02-01'"), "o_orderdate").cast("bigint").alias("age"))


@query("fn_math", "SELECT p_partkey, floor(p_retailprice) AS f, round(sqrt(p_size), 6) AS s, round(ln(p_size), 6) AS l, greatest(p_size, 25) AS g, CAST(p_partkey % 7 AS BIGINT) AS m, abs(p_size - 25) AS a FROM part")
def _(t):
    return t.part.select("p_partkey", F.floor("p_retailprice").cast("double").alias("f"), F.round(F.sqrt("p_size"), 6).alias("s"), F.round(F.log("p_size"), 6).alias("l"), F.greatest("p_size", F.lit(25)).alias("g"), F.pmod("p_partkey", F.lit(7)).alias("m"), F.abs(F.col("p_size") - 25).alias("a"))


@query("fn_array", r"SELECT doc_id, len(list_distinct(w)) AS n, array_to_string(list_sort(list_distinct(w))[1:3], ' ') AS f FROM (SELECT doc_id, string_split(text, ' ') AS w FROM documents)")
def _(t):
    d = t.documents.withColumn("w", F.array_distinct(F.split("text", " ")))
    return d.select("doc_id", F.size("w").cast("bigint").alias("n"), F.array_join(F.slice(F.array_sort("w"), 1, 3), " ").alias("f"))


@query("fn_vector_norm", "SELECT vec_id, round(sqrt(list_sum([CAST(x AS DOUBLE) * x FOR x IN embedding])), 4) AS norm FROM embeddings")
def _(t):
    return t.embeddings.select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 4).alias("norm"))


@query("fn_dot", "SELECT vec_id, round(list_sum([CAST(embedding[i] AS DOUBLE) * i FOR i IN range(1, 65)]), 3) AS dot FROM embeddings")
def _(t):
    products = F.zip_with("embedding", F.sequence(F.lit(1), F.lit(64)), lambda x, i: x.cast("double") * i)
    return t.embeddings.select("vec_id", F.round(F.aggregate(products, F.lit(0.0), lambda a, x: a + x), 3).alias("dot"))


@query("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS INT) AS k FROM events")
def _(t):
    return t.events.select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("fn_variant", "SELECT event_id, CAST(json_extract(props, '$.k') AS INT) AS k FROM events")
def _(t):
    return t.events.select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@query("fn_map", "SELECT l_orderkey, l_linenumber, l_suppkey, CASE l_returnflag WHEN 'A' THEN 1 WHEN 'N' THEN 2 ELSE 3 END AS code FROM lineitem")
def _(t):
    codes = F.map_from_arrays(F.array(*map(F.lit, "ANR")), F.array(F.lit(1), F.lit(2), F.lit(3)))
    return t.lineitem.select("l_orderkey", "l_linenumber", "l_suppkey", codes[F.col("l_returnflag")].alias("code"))


@query("fn_null", "SELECT o_orderkey, coalesce(nullif(o_orderstatus, 'F'), 'done') AS s, TRY_CAST(o_orderpriority AS INT) AS p FROM orders")
def _(t):
    return t.orders.select("o_orderkey", F.coalesce(F.nullif("o_orderstatus", F.lit("F")), F.lit("done")).alias("s"), F.col("o_orderpriority").try_cast("int").alias("p"))


def _sql(name: str, sql: str) -> None:
    """The same SQL on both sides: views of the tables it reads are registered first."""

    @query(name, sql)
    def _(t):
        for table in ("orders", "customer", "nation", "region"):
            getattr(t, table).createOrReplaceTempView(table)
        return t.spark.sql(sql)


_sql("sql_scalar_sub", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT max(o_totalprice) * 0.9 FROM orders)")
_sql("sql_correlated", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000)")
_sql("sql_cte", "WITH RECURSIVE n(k) AS (SELECT 1 UNION ALL SELECT k + 1 FROM n WHERE k < 10) SELECT k, k * k AS square, count(o_orderkey) AS n_orders FROM n LEFT JOIN orders ON o_orderkey % 10 + 1 = k GROUP BY k")


_TAX = "SELECT l_orderkey, l_linenumber, l_suppkey, l_extendedprice * (1 + l_tax) AS gross FROM lineitem"


@query("udf_row", _TAX)
def _(t):
    gross = F.udf(lambda p, x: p * (1 + x), "double")
    return t.lineitem.select("l_orderkey", "l_linenumber", "l_suppkey", gross("l_extendedprice", "l_tax").alias("gross"))


@query("udf_arrow", _TAX)
def _(t):
    def gross(p: pd.Series, x: pd.Series) -> pd.Series:
        return p * (1 + x)

    return t.lineitem.select("l_orderkey", "l_linenumber", "l_suppkey", F.pandas_udf(gross, "double")("l_extendedprice", "l_tax").alias("gross"))


@query("udf_grouped", "SELECT o_orderpriority, max(o_totalprice) - min(o_totalprice) AS spread FROM orders GROUP BY 1")
def _(t):
    # partial extremes first: a group is as many rows as there are tasks, however hot its key
    parts = t.orders.select("o_orderpriority", "o_totalprice").groupBy("o_orderpriority", F.spark_partition_id().alias("p")).agg(F.min("o_totalprice").alias("low"), F.max("o_totalprice").alias("high"))

    def spread(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"o_orderpriority": pdf["o_orderpriority"][:1], "spread": [pdf["high"].max() - pdf["low"].min()]})

    return parts.groupBy("o_orderpriority").applyInPandas(spread, "o_orderpriority string, spread double")


@query("udf_map_arrow", "SELECT vec_id, round(list_max(embedding), 5) AS top FROM embeddings")
def _(t):
    def top(batches):
        for pdf in batches:
            yield pd.DataFrame({"vec_id": pdf["vec_id"], "top": [float(max(e)) for e in pdf["embedding"]]})

    return t.embeddings.select("vec_id", "embedding").mapInPandas(top, "vec_id bigint, top double").withColumn("top", F.round("top", 5).cast("float"))


@query("udaf_wavg", "SELECT l_returnflag, round(sum(l_discount * l_quantity) / sum(l_quantity), 6) AS wavg FROM lineitem GROUP BY 1")
def _(t):
    # sums of each task first, so that a hot group is as many rows as there are tasks
    parts = t.lineitem.groupBy("l_returnflag", F.spark_partition_id().alias("p")).agg(F.sum(F.col("l_discount") * F.col("l_quantity")).alias("xw"), F.sum("l_quantity").alias("w"))

    def weighted(xw: pd.Series, w: pd.Series) -> float:
        return float(xw.sum() / w.sum())

    return parts.groupBy("l_returnflag").agg(F.round(F.pandas_udf(weighted, "double")("xw", "w"), 6).alias("wavg"))


@query("udtf_ngrams", "SELECT p_partkey, unnest([p_name[i:i+2] FOR i IN range(1, length(p_name) - 1)]) AS gram FROM part")
def _(t):
    class Grams:
        def eval(self, text: str):
            for i in range(len(text) - 2):
                yield (text[i : i + 3],)

    grams = F.udtf(Grams, returnType="gram string")
    t.spark.udtf.register("weftline_grams", grams)
    t.part.createOrReplaceTempView("weftline_part")
    return t.spark.sql("SELECT p_partkey, gram FROM weftline_part, LATERAL weftline_grams(p_name)")
