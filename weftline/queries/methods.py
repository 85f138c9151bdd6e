"""Queries for the methods, variants, baselines, measures and workloads."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import encoders as enc
from ..operators import models, profile
from ..plans import rewrite
from ..plans.ir import Dag, Node
from ..plans.lowering import lower
from ..plans.pipeline import Pipeline, PipelineBatch, fuse, parse_spec, to_spec
from ..runtime import measures
from ..runtime.cache import Fingerprints, ReuseCache
from ..runtime.executor import ABLATION, Executor, OptFlags, run_optimized, run_sequential, run_thread_parallel
from ..search import loop
from ..streaming import features as stream
from ..workloads import listing as lst
from ..workloads import others
from .base import Tables, query

L = f"({lst.LISTING_SQL})"
TRAIN = f"(SELECT * FROM {L} WHERE bucket < 8)"


def _listing(t: Tables, columns: list[str] | None = None) -> DataFrame:
    return lst.listing(t.spark, t.sf_dir, columns)


def _frame(t: Tables, node: Node, flags: OptFlags = OptFlags(reuse=False)) -> DataFrame:
    """A plan's last frame through rewriting, lowering and the executor."""
    ex = Executor(t.spark, t.sf_dir, flags)
    dag, _ = ex.plan(Dag({"q": node}))
    ex.bind(dag)
    value = ex._value(dag.sinks["q"], "q", {})
    return getattr(value, "df", value)


def _values(t: Tables, rows: list[tuple], schema: str) -> DataFrame:
    return t.spark.createDataFrame(rows, schema)


def _trials(t: Tables, trials: list[dict]) -> DataFrame:
    return _values(t, [(x["pipeline_id"], None if x["value"] is None else float(x["value"]), x["status"]) for x in trials], "pipeline_id string, value double, status string")


# A. abstraction


@query("listing_view", lst.LISTING_SQL)
def _(t):
    return _listing(t)


_A1 = "SELECT l_orderkey, l_suppkey, price * 2 AS twice FROM " + L + " WHERE bucket = 3"


@query("a1_lazy_pipeline", _A1)
def _(t):
    p = Pipeline.read("listing").map(twice="price * 2").select("bucket = 3").project("l_orderkey", "l_suppkey", "twice")
    return _frame(t, p.node)


@query("a2_wrapped_udf", "SELECT p_partkey, p_size * 3 AS triple FROM part")
def _(t):
    def triple(batches):
        for pdf in batches:
            yield pdf.assign(triple=pdf["p_size"] * 3)[["p_partkey", "triple"]]

    return _frame(t, Pipeline.read("part").call(triple, shape="map", out_schema="p_partkey bigint, triple int").node)


@query("a6_spec_roundtrip", _A1)
def _(t):
    p = Pipeline.read("listing").map(twice="price * 2").select("bucket = 3").project("l_orderkey", "l_suppkey", "twice")
    return _frame(t, parse_spec(to_spec(p)).node)


# B. fusion and rewrites


@query("b3_cse_prep_once", "SELECT * FROM (VALUES ('APPLY_PREP', 4, 2), ('FIT_PREP', 4, 2), ('READ', 4, 1)) AS v(op, before, after)")
def _(t):
    before = fuse(lst.fused_four())
    after = lower(rewrite.cse(before))
    ex = Executor(t.spark, t.sf_dir, OptFlags(reuse=False))
    ex.bind(after)
    for name, sink in after.sinks.items():
        ex._value(sink, name, {})
    computed = [n.op for n in after.nodes() if n.key in ex.observed]
    return _values(t, [(op, before.count(op), computed.count(op)) for op in ("READ", "FIT_PREP", "APPLY_PREP")], "op string, before int, after int")


@query("b4_shared_read", "SELECT p_partkey AS id, p_size AS v FROM part UNION ALL SELECT p_partkey, CAST(length(p_name) AS INT) FROM part")
def _(t):
    a = Pipeline.read("part", columns=["p_partkey", "p_size"]).map(id="p_partkey", v="p_size").project("id", "v")
    b = Pipeline.read("part", columns=["p_name", "p_partkey"]).map(id="p_partkey", v="length(p_name)").project("id", "v")
    dag = rewrite.cse(rewrite.shared_reads(fuse(PipelineBatch((a.named("a"), b.named("b"))))))
    assert dag.count("READ") == 1
    return _frame(t, dag.sinks["a"]).unionByName(_frame(t, dag.sinks["b"]))


@query("b6_constant_fold", "SELECT p_partkey, 10 AS c FROM part")
def _(t):
    p = Pipeline.read("part").select("1 = 1").map(c="2 * 3 + 4").project("p_partkey", "c")
    return _frame(t, rewrite.fold_constants(Dag({"q": p.node})).sinks["q"])


@query("b10_vectorized", "SELECT p_partkey, CASE WHEN p_size > 25 THEN p_size * 2 ELSE p_size - 1 END AS v FROM part")
def _(t):
    udf = Node("UDF", {"shape": "row", "fn": lambda p_size: p_size * 2 if p_size > 25 else p_size - 1, "cols": ["p_size"], "out": "v", "schema": "int"}, (Node("READ", {"source": "part"}),))
    dag = rewrite.vectorize(Dag({"q": Node("PROJECT", {"columns": ["p_partkey", "v"]}, (udf,))}))
    return _frame(t, dag.sinks["q"])


@query("b11_merged_fit", f"SELECT round(avg(p_retailprice), 4) AS mean_price, quantile_cont(size_m, 0.5) AS median_size FROM {TRAIN}")
def _(t):
    a, b = {"kind": "numeric", "cols": ["p_retailprice"]}, {"kind": "numeric", "cols": ["size_m"], "impute": "median"}
    states = enc.fit_all(_listing(t), [a, b], "bucket < 8", "price")
    row = (round(states[enc.key_of(a)]["p_retailprice"][0], 4), states[enc.key_of(b)]["size_m"][0])
    return _values(t, [row], "mean_price double, median_size double")


@query("b12_equivalence", "SELECT CAST(NULL AS BIGINT) AS l_orderkey, CAST(NULL AS BIGINT) AS twice WHERE false")
def _(t):
    p = Pipeline.read("listing").map(twice="price * 2").map(more="price + 1").select("bucket = 3").project("l_orderkey", "twice")
    plain, fast = _frame(t, p.node, OptFlags(False, True, False, False)), _frame(t, p.node)
    return plain.exceptAll(fast).unionAll(fast.exceptAll(plain))


# C. lowering


@query("c2_auto_encode", f"""WITH s AS (SELECT avg(p_retailprice) AS m, stddev_pop(p_retailprice) AS sd FROM {TRAIN})
SELECT l_orderkey, l_linenumber, l_suppkey, round((p_retailprice - m) / sd, 5) AS scaled, CAST(l_returnflag = 'N' AS DOUBLE) AS flag_n, CAST(l_returnflag = 'R' AS DOUBLE) AS flag_r FROM {L}, s""")
def _(t):
    cols = ["p_retailprice", "l_returnflag"]
    carry = ["l_orderkey", "l_linenumber", "l_suppkey"]
    p = Pipeline.read("listing").auto_prepare("bucket < 8", "price", columns=cols, carry=carry)
    return _frame(t, p.node).select(*carry, F.round("f_p_retailprice", 5).alias("scaled"), F.col("f_l_returnflag_0").alias("flag_n"), F.col("f_l_returnflag_1").alias("flag_r"))


_SLOPE = "(n * sxy - sx * sy) / (n * sxx - sx * sx)"
_FOLD_SUMS = f"SELECT fold, count(*) AS n, sum(p_retailprice) AS sx, sum(price) AS sy, sum(p_retailprice * p_retailprice) AS sxx, sum(p_retailprice * price) AS sxy FROM {TRAIN} GROUP BY fold"


@query("c3_cv_folds", f"""WITH f AS ({_FOLD_SUMS}), a AS (SELECT sum(n) AS n, sum(sx) AS sx, sum(sy) AS sy, sum(sxx) AS sxx, sum(sxy) AS sxy FROM f),
r AS (SELECT f.fold, a.n - f.n AS n, a.sx - f.sx AS sx, a.sy - f.sy AS sy, a.sxx - f.sxx AS sxx, a.sxy - f.sxy AS sxy FROM f, a)
SELECT fold, CAST(n AS BIGINT) AS n_train, round({_SLOPE}, 2) AS slope FROM r""")
def _(t):
    rows = _listing(t, ["p_retailprice", "price", "bucket", "fold"]).filter("bucket < 8")
    sums = models.moments(rows, ["p_retailprice"], "price", "fold")
    total = sum(sums.values())
    out = [(int(f), int((total - m)[0, 0]), round(models.solve_ridge(total - m, 0.0)["w"][0], 2)) for f, m in sorted(sums.items())]
    return _values(t, out, "fold int, n_train bigint, slope double")


@query("c4_grid", f"""WITH f AS (SELECT count(*) AS n, sum(p_retailprice) AS sx, sum(price) AS sy, sum(p_retailprice * p_retailprice) AS sxx, sum(p_retailprice * price) AS sxy FROM {TRAIN})
SELECT alpha, round((sxy - sx * sy / n) / (sxx - sx * sx / n + alpha), 2) AS slope FROM f, (VALUES (CAST(0 AS DOUBLE)), (1000), (1000000)) AS g(alpha)""")
def _(t):
    m = models.moments(_listing(t, ["p_retailprice", "price", "bucket"]).filter("bucket < 8"), ["p_retailprice"], "price")[0]
    return _values(t, [(a, round(models.solve_ridge(m, a)["w"][0], 2)) for a in (0.0, 1000.0, 1000000.0)], "alpha double, slope double")


@query("c6_rowwise_fusion", "SELECT p_partkey, p_size + 1 AS a, p_size * 2 AS b FROM part WHERE p_size > 10")
def _(t):
    p = Pipeline.read("part").map(a="p_size + 1").map(b="p_size * 2").select("p_size > 10").project("p_partkey", "a", "b", "p_size").project("p_partkey", "a", "b")
    return _frame(t, p.node)


# D. selection


@query("d5_impl_agreement", "SELECT 3 AS implementations, true AS agree")
def _(t):
    rows = _listing(t, ["size_m", "p_retailprice", "price", "bucket"]).filter("bucket < 8").select(F.coalesce("size_m", F.lit(25)).alias("size_m"), "p_retailprice", "price")
    names = ["size_m", "p_retailprice"]
    expressions, blocks, by_row = (models.moments(rows, names, "price", kernel=k)[0] for k in ("expressions", "blocks", "rows"))
    agree = bool(np.allclose(expressions, by_row, rtol=1e-9) and np.allclose(expressions, blocks, rtol=1e-9))
    return _values(t, [(3, agree)], "implementations int, agree boolean")


# E. operators


@query("e2_clean", f"SELECT l_orderkey, l_linenumber, l_suppkey, CASE WHEN lower(trim(segment_raw)) IN ('', 'n/a', 'na', 'null', 'none', 'nan', '-') THEN NULL ELSE trim(segment_raw) END AS segment FROM {L}")
def _(t):
    return _listing(t).select("l_orderkey", "l_linenumber", "l_suppkey", enc.cleaned(F.col("segment_raw")).alias("segment"))


for _how, _sql in {"mean": "round(avg(size_m), 5)", "median": "quantile_cont(size_m, 0.5)", "const": "-1", "mode": "(SELECT size_m FROM v WHERE size_m IS NOT NULL GROUP BY size_m ORDER BY count(*) DESC, size_m LIMIT 1)"}.items():

    @query(f"e3_impute_{_how}", f"WITH v AS (SELECT size_m FROM {TRAIN}), s AS (SELECT CAST({_sql} AS DOUBLE) AS fill{' FROM v' if _how in ('mean', 'median') else ''}) SELECT l_orderkey, l_linenumber, l_suppkey, coalesce(CAST(size_m AS DOUBLE), fill) AS size_filled, CAST(size_m IS NULL AS INT) AS was_missing FROM {L}, s")
    def _(t, how=_how):
        df = _listing(t)
        fill = df.filter("bucket < 8").agg(F.round(enc.impute_value("size_m", how, -1).cast("double"), 5).alias("fill"))
        return df.crossJoin(F.broadcast(fill)).select("l_orderkey", "l_linenumber", "l_suppkey", F.coalesce(F.col("size_m").cast("double"), "fill").alias("size_filled"), F.col("size_m").isNull().cast("int").alias("was_missing"))


def _encoded(t, encoder: dict, carry=("l_orderkey", "l_linenumber", "l_suppkey", "bucket", "fold")):
    df = _listing(t)
    states = enc.fit_all(df, [encoder], "bucket < 8", "price")
    return enc.apply_all(df, [encoder], states, list(carry), "bucket < 8")[0]


@query("e4_onehot", f"SELECT l_orderkey, l_linenumber, l_suppkey, CAST(l_returnflag = 'A' AS DOUBLE) AS a, CAST(l_returnflag = 'N' AS DOUBLE) AS n, CAST(l_returnflag = 'R' AS DOUBLE) AS r FROM {L}")
def _(t):
    df = _encoded(t, {"kind": "onehot", "cols": ["l_returnflag"], "drop_first": False})
    return df.select("l_orderkey", "l_linenumber", "l_suppkey", *[F.col(f"f_l_returnflag_{k}").alias(c) for k, c in enumerate("anr")])


@query("e4_onehot_rare", f"""WITH c AS (SELECT p_brand, count(*) AS n FROM {TRAIN} GROUP BY 1), m AS (SELECT quantile_disc(n, 0.5) AS least FROM c)
SELECT l_orderkey, l_linenumber, l_suppkey, CAST(p_brand IN (SELECT p_brand FROM c, m WHERE n < least) AS DOUBLE) AS rare FROM {L}""")
def _(t):
    least = _listing(t).filter("bucket < 8").groupBy("p_brand").count().agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY count)").alias("m")).first()["m"]
    df = _encoded(t, {"kind": "onehot", "cols": ["p_brand"], "min_count": int(least)})
    rare = F.col("f_p_brand_rare") if "f_p_brand_rare" in df.columns else F.lit(0.0)
    return df.select("l_orderkey", "l_linenumber", "l_suppkey", rare.alias("rare"))


_PADDED = "' ' || lower(trim(p_name)) || ' '"


@query("e5_ngrams", f"SELECT gram, CAST(count(*) AS BIGINT) AS n FROM (SELECT unnest([t[i:i+2] FOR i IN range(1, length(t) - 1)]) AS gram FROM (SELECT {_PADDED} AS t FROM part)) GROUP BY 1")
def _(t):
    return t.part.select(F.explode(enc.char_ngrams(enc.padded(F.col("p_name")), 3)).alias("gram")).groupBy("gram").agg(F.count("*").alias("n"))


@query("e5_tfidf", f"""WITH s AS (SELECT p_name AS v, {_PADDED} AS t, count(*) AS w FROM part GROUP BY 1, 2), g AS (SELECT v, w, unnest([t[i:i+2] FOR i IN range(1, length(t) - 1)]) AS gram FROM s),
tf AS (SELECT v, w, gram, count(*) AS tf FROM g GROUP BY ALL), df AS (SELECT gram, sum(w) AS df FROM tf GROUP BY 1), n AS (SELECT sum(w) AS n FROM s)
SELECT v, gram, round(tf * (ln((1 + n) / (1 + df)) + 1), 6) AS weight FROM tf JOIN df USING (gram), n""")
def _(t):
    strings = t.part.groupBy(F.col("p_name").alias("v")).agg(F.count("*").alias("w"))
    counts = enc.text_counts(strings, 3)
    total = strings.agg(F.sum("w").alias("total"))
    idf = counts.groupBy("gram").agg(F.sum("w").alias("df")).crossJoin(F.broadcast(total)).select("gram", (F.log((1 + F.col("total")) / (1 + F.col("df"))) + 1).alias("idf"))
    return counts.join(idf, "gram").select("v", "gram", F.round(F.col("tf") * F.col("idf"), 6).alias("weight"))


_TT = f"WITH g AS (SELECT n_name, sum(price) AS s, count(*) AS n FROM {TRAIN} GROUP BY 1), a AS (SELECT sum(s) AS s, sum(n) AS n FROM g)"
for _name, _m in {"plain": 0, "smooth": 50}.items():

    @query(f"e6_target_{_name}", _TT + f" SELECT l_orderkey, l_linenumber, l_suppkey, round((g.s + {_m} * a.s / a.n) / (g.n + {_m}), 3) AS encoded FROM {L} JOIN g USING (n_name), a")
    def _(t, m=_m):
        df = _encoded(t, {"kind": "target", "cols": ["n_name"], "smoothing": float(m)})
        return df.select("l_orderkey", "l_linenumber", "l_suppkey", F.round("f_n_name_mean", 3).alias("encoded"))


@query("e6_target_oof", f"""WITH k AS (SELECT n_name, fold, sum(price) AS s, count(*) AS n FROM {TRAIN} GROUP BY 1, 2), g AS (SELECT n_name, sum(s) AS s, sum(n) AS n FROM k GROUP BY 1),
f AS (SELECT fold, sum(s) AS s, sum(n) AS n FROM k GROUP BY 1), a AS (SELECT sum(s) AS s, sum(n) AS n FROM g)
SELECT l_orderkey, l_linenumber, l_suppkey, round(CASE WHEN bucket < 8 THEN (g.s - coalesce(k.s, 0) + 20 * (a.s - f.s) / (a.n - f.n)) / (g.n - coalesce(k.n, 0) + 20)
 ELSE (g.s + 20 * a.s / a.n) / (g.n + 20) END, 3) AS encoded FROM {L} x JOIN g ON g.n_name = x.n_name LEFT JOIN k ON k.n_name = x.n_name AND k.fold = x.fold JOIN f ON f.fold = x.fold, a""")
def _(t):
    df = _encoded(t, {"kind": "target", "cols": ["n_name"], "smoothing": 20.0, "fold": "fold"})
    return df.select("l_orderkey", "l_linenumber", "l_suppkey", F.round("f_n_name_mean", 3).alias("encoded"))


@query("e7_scale", f"WITH s AS (SELECT avg(p_retailprice) AS m, stddev_pop(p_retailprice) AS sd FROM {TRAIN}) SELECT l_orderkey, l_linenumber, l_suppkey, round((p_retailprice - m) / sd, 5) AS scaled FROM {L}, s")
def _(t):
    df = _encoded(t, {"kind": "numeric", "cols": ["p_retailprice"]})
    return df.select("l_orderkey", "l_linenumber", "l_suppkey", F.round("f_p_retailprice", 5).alias("scaled"))


@query("e8_gram", f"SELECT CAST(count(*) AS DOUBLE) AS n, CAST(sum(p_size) AS DOUBLE) AS sx, CAST(sum(p_size * p_size) AS DOUBLE) AS sxx, CAST(sum(p_size * price) AS DOUBLE) AS sxy FROM (SELECT CAST(coalesce(size_m, 25) AS BIGINT) AS p_size, price FROM {TRAIN})")
def _(t):
    m = models.moments(_listing(t).filter("bucket < 8").select(F.coalesce("size_m", F.lit(25)).alias("p_size"), "price"), ["p_size"], "price")[0]
    return _values(t, [(float(m[0, 0]), float(m[0, 1]), float(m[1, 1]), float(m[1, 2]))], "n double, sx double, sxx double, sxy double")


@query("e8_ridge_1d", f"WITH v AS (SELECT p_retailprice AS x, price AS y FROM {TRAIN}), s AS (SELECT avg(x) AS mx, avg(y) AS my, covar_pop(x, y) * count(*) AS sxy, var_pop(x) * count(*) AS sxx FROM v) SELECT round(sxy / (sxx + 10), 2) AS w, round(my - sxy / (sxx + 10) * mx, 0) AS b FROM s")
def _(t):
    m = models.moments(_listing(t).filter("bucket < 8"), ["p_retailprice"], "price")[0]
    s = models.solve_ridge(m, 10.0)
    return _values(t, [(round(s["w"][0], 2), float(round(s["b"], 0)))], "w double, b double")


_BINNED = f"(SELECT CAST(coalesce(size_m, 0) // 10 AS INT) AS bin, price FROM {TRAIN})"


def _bins(t):
    return _listing(t).filter("bucket < 8").select(F.floor(F.coalesce("size_m", F.lit(0)) / 10).cast("int").alias("bin"), "price")


@query("e10_histogram", f"SELECT bin, CAST(sum(-price) AS BIGINT) AS g, CAST(count(*) AS BIGINT) AS h FROM {_BINNED} GROUP BY 1")
def _(t):
    return _bins(t).groupBy("bin").agg(F.sum(-F.col("price")).alias("g"), F.count("*").alias("h"))


_SPLIT = f"""WITH h AS (SELECT bin, CAST(sum(-price) AS DOUBLE) AS g, CAST(count(*) AS DOUBLE) AS n FROM {_BINNED} WHERE {{where}} GROUP BY 1), a AS (SELECT sum(g) AS g, sum(n) AS n FROM h),
c AS (SELECT bin, sum(g) OVER (ORDER BY bin) AS lg, sum(n) OVER (ORDER BY bin) AS ln FROM h)
SELECT bin, round(0.5 * (lg * lg / (ln + 1) + (a.g - lg) * (a.g - lg) / (a.n - ln + 1) - a.g * a.g / (a.n + 1)) / 1e6, 2) AS gain FROM c, a WHERE a.n > ln ORDER BY gain DESC, bin LIMIT 1"""


def _split(t, rows: DataFrame) -> DataFrame:
    h = np.zeros((1, 7, 2))
    for r in rows.groupBy("bin").agg(F.sum(-F.col("price")).alias("g"), F.count("*").alias("n")).collect():
        h[0, r["bin"]] = r["g"], r["n"]
    gain, _, at = models.best_split(h, 1.0)
    return _values(t, [(at, round(gain / 1e6, 2))], "bin int, gain double")


@query("e10_best_split", _SPLIT.format(where="true"))
def _(t):
    return _split(t, _bins(t))


@query("e11_leafwise_split", _SPLIT.format(where="bin >= 2"))
def _(t):
    return _split(t, _bins(t).filter("bin >= 2"))


@query("e12_gram", "SELECT CAST(i AS INT) AS i, round(sum(CAST(embedding[i] AS DOUBLE) * embedding[1]), 4) AS v FROM embeddings, range(1, 65) AS r(i) GROUP BY 1")
def _(t):
    g = models.gram(t.embeddings.select("embedding"), "embedding")
    return _values(t, [(i + 1, round(float(g[i, 0]), 4)) for i in range(len(g))], "i int, v double")


@query("e13_dateparts", f"SELECT l_orderkey, l_linenumber, l_suppkey, CAST(year(l_shipdate) AS DOUBLE) AS y, CAST(month(l_shipdate) AS DOUBLE) AS m, CAST(dayofweek(l_shipdate) + 1 AS DOUBLE) AS dow, CAST(date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)) AS DOUBLE) AS epoch FROM {L}")
def _(t):
    df = _encoded(t, {"kind": "dates", "cols": ["l_shipdate"]})
    return df.select("l_orderkey", "l_linenumber", "l_suppkey", F.col("f_l_shipdate_year").alias("y"), F.col("f_l_shipdate_month").alias("m"), F.col("f_l_shipdate_dow").alias("dow"), F.col("f_l_shipdate_epoch").alias("epoch"))


@query("e14_folds", f"SELECT bucket, fold, CAST(count(*) AS BIGINT) AS n FROM {L} GROUP BY 1, 2")
def _(t):
    return _listing(t, ["bucket", "fold"]).groupBy("bucket", "fold").agg(F.count("*").alias("n"))


_P = "(SELECT price AS y, 20000 * p_retailprice - 18000000 AS p FROM " + L + ")"


@query("e15_metrics_reg", f"SELECT round(sqrt(avg((p - y) * (p - y))), 1) AS rmse, round(avg(abs(p - y)), 1) AS mae FROM {_P}")
def _(t):
    df = _listing(t, ["price", "p_retailprice"]).withColumn("prediction", 20000 * F.col("p_retailprice") - 18000000)
    m = models.regression_measures("price")
    return df.agg(F.round(m["rmse"], 1).alias("rmse"), F.round(m["mae"], 1).alias("mae"))


@query("e15_metrics_cls", "WITH v AS (SELECT toxic AS y, CAST(n_chars % 100 AS DOUBLE) / 100 AS p FROM documents JOIN labels USING (doc_id)) SELECT round(avg(CAST((p > 0.5) = (y = 1) AS INT)), 6) AS accuracy, round(2 * sum(CASE WHEN p > 0.5 AND y = 1 THEN 1 ELSE 0 END) / (sum(CASE WHEN p > 0.5 THEN 1 ELSE 0 END) + sum(y)), 6) AS f1 FROM v")
def _(t):
    df = t.documents.join(t.labels, "doc_id").select(F.col("toxic").alias("y"), ((F.col("n_chars") % 100) / 100).alias("p"))
    m = models.class_measures("y", "p")
    return df.agg(F.round(m["accuracy"], 6).alias("accuracy"), F.round(m["f1"], 6).alias("f1"))


@query("e15_auc", "WITH v AS (SELECT toxic AS y, n_chars % 50 AS s FROM documents JOIN labels USING (doc_id)), r AS (SELECT y, rank() OVER (ORDER BY s) + (count(*) OVER (PARTITION BY s) - 1) / 2 AS k FROM v) SELECT round((sum(k) FILTER (WHERE y = 1) - sum(y) * (sum(y) + 1) / 2) / (sum(y) * (count(*) - sum(y))), 6) AS auc FROM r")
def _(t):
    df = t.documents.join(t.labels, "doc_id").select(F.col("toxic").alias("y"), (F.col("n_chars") % 50).alias("s"))
    return models.auc(df, "y", "s").select(F.round("auc", 6).alias("auc"))


@query("e17_quantize", "SELECT vec_id, CAST(max(abs(q)) AS INT) AS top FROM (SELECT vec_id, unnest([CAST(round(CAST(x AS DOUBLE) / (list_max([abs(CAST(y AS DOUBLE)) FOR y IN embedding]) / 127)) AS INT) FOR x IN embedding]) AS q FROM embeddings) GROUP BY 1")
def _(t):
    q = models.quantize(F.transform("embedding", lambda x: x.cast("double")))
    return t.embeddings.select("vec_id", F.array_max(F.transform(q["q"], lambda x: F.abs(x))).alias("top"))


_NAMES = "SELECT DISTINCT p_name FROM part"


@query("e19_match", f"WITH n AS ({_NAMES}) SELECT a.p_name AS left_value, b.p_name AS right_value, round(1 - levenshtein(a.p_name, b.p_name) / greatest(length(a.p_name), length(b.p_name)), 6) AS similarity FROM n a JOIN n b ON substr(a.p_name, 1, 2) = substr(b.p_name, 1, 2) AND a.p_name < b.p_name WHERE round(1 - levenshtein(a.p_name, b.p_name) / greatest(length(a.p_name), length(b.p_name)), 6) >= 0.5")
def _(t):
    return profile.match_entities(t.part, t.part, "p_name", F.expr("substring(left_value, 1, 2)"), 0.5)


@query("e19_match_everywhere", f"WITH n AS ({_NAMES}) SELECT a.p_name AS left_value, b.p_name AS right_value, round(1 - levenshtein(a.p_name, b.p_name) / greatest(length(a.p_name), length(b.p_name)), 6) AS similarity FROM n a JOIN n b ON a.p_name < b.p_name WHERE round(1 - levenshtein(a.p_name, b.p_name) / greatest(length(a.p_name), length(b.p_name)), 6) >= 0.5")
def _(t):
    return profile.match_everywhere(t.part, t.part, "p_name", 0.5)


@query("e19_errors", f"SELECT l_orderkey, l_linenumber, l_suppkey, r AS rule FROM {L}, (VALUES ('dirty segment'), ('long discount')) AS v(r) WHERE (r = 'dirty segment' AND trim(segment_raw) IN ('', 'N/A')) OR (r = 'long discount' AND quantity_m > 48)")
def _(t):
    rules = {"dirty segment": "trim(segment_raw) NOT IN ('', 'N/A')", "long discount": "quantity_m <= 48"}
    return profile.detect_errors(_listing(t), rules, ["l_orderkey", "l_linenumber", "l_suppkey"])


@query("e20_semantic_filter", "SELECT doc_id, contains(lower(text), 'license') AS decision FROM documents")
def _(t):
    return profile.semantic_filter(t.documents, "text", lambda x: "license" in x.lower()).select("doc_id", "decision")


# F, G, H


@query("f1_parallel_equals_serial", "SELECT 4 AS pipelines, true AS equal")
def _(t):
    serial = run_optimized(t.spark, t.sf_dir, lst.fused_four(), flags=ABLATION["selection"])
    threads = run_optimized(t.spark, t.sf_dir, lst.fused_four(), flags=ABLATION["parallel"])
    return _values(t, [(4, same_trials(serial, threads))], "pipelines int, equal boolean")


def same_trials(a, b) -> bool:
    x, y = ({r["pipeline_id"]: r["value"] for r in z.trials} for z in (a, b))
    return x.keys() == y.keys() and all(abs(x[k] - y[k]) <= 1e-9 * abs(x[k]) for k in x)


@query("g1_fingerprint", "SELECT * FROM (VALUES ('file state', true), ('same plan', true), ('other parameter', false), ('other seed', false)) AS v(compared, equal)")
def _(t):
    prints = Fingerprints(t.spark, t.sf_dir)
    a, b = Pipeline.read("part").map(x="p_size + 1"), Pipeline.read("part").map(x="p_size + 2")
    seeded = lambda s: Pipeline.read("part").call(len, seed=s, deterministic=False).node
    same = Pipeline.read("part").map(x="p_size + 1")

    def rows_of(p: Pipeline) -> tuple:
        """The frame's rows as their number and a sum of hashes, by a scan of the table."""
        df = _frame(t, p.node)
        return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64(*df.columns).cast("decimal(38,0)"))).first())

    plan, again, other = map(rows_of, (a, same, b))  # equal prints stand for equal rows, other prints for others
    rows = [("same plan", prints.of(a.node) == prints.of(same.node) and plan == again), ("other parameter", prints.of(a.node) == prints.of(b.node) or plan == other), ("other seed", seeded(1).key == seeded(2).key), ("file state", prints.of(a.node) == Fingerprints(t.spark, t.sf_dir).of(a.node))]
    return _values(t, rows, "compared string, equal boolean")


@query("g3_reuse_equals_recompute", "SELECT true AS equal, true AS had_hits")
def _(t):
    cache = ReuseCache(t.spark, t.sf_dir)
    first = run_optimized(t.spark, t.sf_dir, lst.fused_four(), cache=cache)
    again = run_optimized(t.spark, t.sf_dir, lst.fused_four(), cache=cache)
    return _values(t, [(same_trials(first, again), cache.stats["hits"] >= 2)], "equal boolean, had_hits boolean")


@query("h5_incremental_equals_batch", "SELECT true AS equal")
def _(t):
    whole = run_optimized(t.spark, t.sf_dir, lst.fused_four(), flags=OptFlags(reuse=False))
    parts = {x["pipeline_id"]: x["value"] for x in loop.run_incremental(t.spark, t.sf_dir, lst.fused_four())}
    return _values(t, [(all(abs(parts[x["pipeline_id"]] - x["value"]) < 1e-6 * x["value"] for x in whole.trials),)], "equal boolean")


@query("h8_infeasible", "SELECT * FROM (VALUES ('failing/ridge', 'failed: ValueError'), ('scaled/ridge', 'ok'), ('wide/ridge', 'infeasible')) AS v(pipeline_id, status)")
def _(t):
    return _trials(t, run_optimized(t.spark, t.sf_dir, lst.infeasible(), flags=OptFlags(reuse=False)).trials).select("pipeline_id", "status")


# I. profiles

_NUMS = ("l_quantity", "l_extendedprice", "l_discount")


@query("i1_missing_ratio", " UNION ALL ".join(f"SELECT '{c}' AS column_name, avg(CAST({c} IS NULL AS INT)) AS missing_ratio FROM {L}" for c in ("size_m", "quantity_m", "price")))
def _(t):
    return profile.profile_missing(_listing(t), ["size_m", "quantity_m", "price"])


@query("i2_cardinality", " UNION ALL ".join(f"SELECT '{c}' AS column_name, CAST(count(DISTINCT {c}) AS BIGINT) AS n_distinct FROM lineitem" for c in ("l_partkey", "l_suppkey", "l_returnflag")))
def _(t):
    return profile.profile_cardinality(t.lineitem, ["l_partkey", "l_suppkey", "l_returnflag"])


@query("i3_vocab", r"WITH c AS (SELECT token, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '[^ \t\n\r\f\v]+')) AS token FROM documents) GROUP BY 1) SELECT CAST(sum(n) AS BIGINT) AS n_tokens, CAST(count(*) AS BIGINT) AS n_types, round(count(*) / sum(n), 6) AS type_token_ratio, round(avg(CAST(n = 1 AS INT)), 6) AS hapax_share FROM c")
def _(t):
    return profile.profile_vocabulary(t.documents, "text")


@query("i4_numeric_profile", " UNION ALL ".join(f"SELECT '{c}' AS column_name, '{s}' AS statistic, CAST({e.format(c=c)} AS DOUBLE) AS value FROM lineitem" for c in _NUMS for s, e in {"min": "min({c}) + 0", "max": "max({c})", "mean": "round(avg({c}), 4)", "std": "round(stddev_pop({c}), 4)", "median": "quantile_cont({c}, 0.5)"}.items()))
def _(t):
    return profile.profile_numeric(t.lineitem, list(_NUMS))


@query("i4_top_values", "SELECT p_brand AS value, CAST(count(*) AS BIGINT) AS n FROM part GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 5")
def _(t):
    return profile.top_values(t.part, "p_brand")


@query("i5_dense_profile", "SELECT CAST(min(len(embedding)) AS INT) AS min_size, CAST(max(len(embedding)) AS INT) AS max_size, round(avg(sqrt(list_sum([CAST(x AS DOUBLE) * x FOR x IN embedding]))), 4) AS mean_norm FROM embeddings")
def _(t):
    return profile.profile_dense(t.embeddings, "embedding")


@query("i6_hash_sample", "SELECT l_orderkey, l_linenumber, l_suppkey FROM lineitem WHERE (l_orderkey * 7919 + 7) % 100 < 10")
def _(t):
    return profile.hash_sample(t.lineitem, "l_orderkey", 10).select("l_orderkey", "l_linenumber", "l_suppkey")


@query("i8_task_kind", "SELECT * FROM (VALUES ('price', 'regression'), ('l_returnflag', 'classification'), ('bucket', 'classification')) AS v(target, task)")
def _(t):
    df = _listing(t)
    return _values(t, [(c, profile.infer_task(df, c)) for c in ("price", "l_returnflag", "bucket")], "target string, task string")


# measures, baselines and workloads


@query("m6_changed_lines", """WITH l AS (SELECT conv_id, turn, list_distinct(string_split(text, chr(10))) AS lines FROM conversations),
b AS (SELECT *, lag(lines) OVER (PARTITION BY conv_id ORDER BY turn) AS before FROM l)
SELECT conv_id, turn AS version, round(len([x FOR x IN lines IF NOT list_contains(before, x)]) / len(lines), 6) AS changed_ratio FROM b WHERE before IS NOT NULL""")
def _(t):
    return measures.changed_line_sets(t.conversations.select("conv_id", F.col("turn").alias("version"), "text"), "conv_id")


@query("m7_utilization", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS bucket_start, round(avg(value), 4) AS mean_value, max(value) AS max_value, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")
def _(t):
    return measures.utilization(t.events.select(F.col("ts").cast("timestamp").alias("ts"), "value"), "1 day")


@query("w8_churn", others.CHURN_SQL)
def _(t):
    return others.churn(t.spark, t.sf_dir)


@query("w11_text_features", others.TEXT_SQL)
def _(t):
    return others.text_features(t.spark, t.sf_dir)


@query("w14_streamed_specs", "SELECT 4 AS pipelines, true AS equal")
def _(t):
    from ..sources.files import scratch

    folder, got = scratch(t.spark, "specs"), {}
    pipes = lst.fused_four().pipelines
    _values(t, [(to_spec(p),) for p in pipes], "value string").repartition(2).write.text(folder)
    cache = ReuseCache(t.spark, t.sf_dir)

    def handle(specs: list[str]) -> None:
        if specs:
            batch = PipelineBatch(tuple(parse_spec(s) for s in specs))
            got.update({x["pipeline_id"]: x["value"] for x in run_optimized(t.spark, t.sf_dir, batch, cache=cache).trials})

    stream.stream_batches(t.spark, folder, handle)
    whole = run_optimized(t.spark, t.sf_dir, lst.fused_four(), flags=OptFlags(reuse=False))
    return _values(t, [(len(got), all(abs(got[x["pipeline_id"]] - x["value"]) < 1e-6 * x["value"] for x in whole.trials))], "pipelines int, equal boolean")


# streams

_EV = "FROM events GROUP BY 1, 2"


@query("str_tumbling", f"SELECT time_bucket(INTERVAL 1 DAY, ts) AS window_start, event_type, CAST(count(*) AS BIGINT) AS n {_EV}")
def _(t):
    return stream.bounds(stream.run_available(stream.windows(stream.event_stream(t.spark, t.sf_dir), "1 day"), "complete"), "event_type", "n")


@query("str_sliding", f"SELECT time_bucket(INTERVAL 12 HOURS, ts) - k * INTERVAL 12 HOURS AS window_start, event_type, CAST(count(*) AS BIGINT) AS n FROM events, range(0, 2) AS r(k) GROUP BY 1, 2")
def _(t):
    return stream.bounds(stream.run_available(stream.windows(stream.event_stream(t.spark, t.sf_dir), "1 day", "12 hours"), "complete"), "event_type", "n")


@query("str_session", """WITH d AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 2 HOURS THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM d) SELECT min(ts) AS window_start, user_id, CAST(count(*) AS BIGINT) AS n FROM s GROUP BY user_id, k""")
def _(t):
    return stream.bounds(stream.run_available(stream.sessions(stream.event_stream(t.spark, t.sf_dir), "2 hours"), "complete"), "user_id", "n")


@query("str_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def _(t):
    s = stream.event_stream(t.spark, t.sf_dir).withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return stream.run_available(s.select("user_id", "event_type"))


@query("str_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
def _(t):
    s = stream.event_stream(t.spark, t.sf_dir).join(t.customer, F.col("c_custkey") == F.col("user_id"))
    return stream.run_available(s.select("event_id", "c_mktsegment"))


@query("str_stream_join", "SELECT a.event_id AS click_id, b.event_id AS buy_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(t):
    a = stream.event_stream(t.spark, t.sf_dir).filter("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("click_ts")).withWatermark("click_ts", "3650 days")
    b = stream.event_stream(t.spark, t.sf_dir).filter("event_type = 'purchase'").select(F.col("user_id").alias("buyer"), F.col("event_id").alias("buy_id"), F.col("ts").alias("buy_ts")).withWatermark("buy_ts", "3650 days")
    return stream.run_available(a.join(b, F.expr("user_id = buyer AND buy_ts >= click_ts AND buy_ts <= click_ts + INTERVAL 1 HOUR")).select("click_id", "buy_id"))


@query("str_running_state", "SELECT user_id, CAST(count(*) AS BIGINT) AS n, round(sum(value), 3) AS total FROM events GROUP BY 1")
def _(t):
    updates = stream.run_available(stream.running_state(stream.event_stream(t.spark, t.sf_dir)), "update")
    return updates.groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max_by("total", "n"), 3).alias("total"))
