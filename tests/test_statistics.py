import numpy as np
import pytest

from weftline.operators import encoders as enc
from weftline.operators import merge, models, order


@pytest.mark.parametrize("most", [order.MOST_VALUES, 5])
def test_exact_quantiles(spark, monkeypatch, most):
    monkeypatch.setattr(order, "MOST_VALUES", most)
    rng = np.random.default_rng(4)
    a, b = rng.normal(size=501), rng.integers(0, 3, 501).astype(float)
    rows = [(float(x), float(y), None, 7.0) for x, y in zip(a, b)]
    df = spark.createDataFrame(rows, "a double, b double, none double, same double").repartition(3)
    for share in (0.5, 0.25, 0.0, 1.0):
        got = order.exact_quantiles(df, ["a", "b", "none", "same"], share)
        assert got["a"] == pytest.approx(np.quantile(a, share)) and got["b"] == np.quantile(b, share)
        assert (got["none"], got["same"]) == (None, 7.0)
    assert order.exact_quantiles(df.limit(0), ["a"]) == {"a": None}


def test_auc_in_ranges(spark, monkeypatch):
    monkeypatch.setattr(order, "RANGES", 7)
    rng = np.random.default_rng(5)
    y, s = rng.integers(0, 2, 400), rng.integers(0, 60, 400) / 10
    got = order.auc(spark.createDataFrame([(int(a), float(b)) for a, b in zip(y, s)], "y int, s double").repartition(4), "y", "s").first()[0]
    pos, neg = s[y == 1], s[y == 0]
    assert got == pytest.approx(np.mean([(p > neg).mean() + (p == neg).mean() / 2 for p in pos]))


def test_sums_are_merged_in_rounds(spark, monkeypatch):
    monkeypatch.setattr(merge, "DRIVER_PARTS", 1)
    x = np.random.default_rng(6).normal(size=(300, 3)) + 1e6
    df = spark.createDataFrame([tuple(map(float, r)) for r in x], "a double, b double, y double").repartition(6)
    z = np.column_stack([np.ones(300), x])
    for kernel in ("expressions", "blocks", "rows"):
        m = models.moments(df, ["a", "b"], "y", kernel=kernel)[0]
        assert np.allclose(m, z.T @ z, rtol=1e-12)
        assert np.allclose(models.centred(m)[0], np.cov(x[:, :2].T, bias=True) * 300, rtol=1e-6)


def test_missing_values_go_the_better_way(spark):
    rows = [(None if k % 3 == 0 else float(k % 10), float(100 if k % 3 == 0 or k % 10 > 5 else 0)) for k in range(300)]
    df = spark.createDataFrame(rows, "a double, y double").repartition(2)
    model = models.boost(df, ["a"], "y", trees=6, depth=1, eta=1.0, lam=1e-9)
    errors = df.select((models.prediction(model, ["a"]) - df["y"]).alias("e")).toPandas()["e"]
    assert np.abs(errors).max() < 1e-6
    assert model["trees"][0][0][5] is False


def test_row_form_equals_expressions(spark):
    rows = [(float(k % 7) if k % 5 else None, "xyz"[k % 3], k % 2, k % 4, float(k)) for k in range(60)]
    df = spark.createDataFrame(rows, "n double, c string, t int, fold int, y double").repartition(3)
    encoders = [
        {"kind": "numeric", "cols": ["n"], "impute": "median", "indicator": True}, {"kind": "onehot", "cols": ["c"]},
        {"kind": "target", "cols": ["c"], "fold": "fold", "smoothing": 3.0}, {"kind": "text", "cols": ["c"], "n_components": 2},
    ]
    states = enc.fit_all(df, encoders, "t = 0", "y")
    (a, names), (b, same) = (f(df, encoders, states, ["y"], "t = 0") for f in (enc.apply_all, enc.apply_rows))
    assert names == same
    x, y = (d.orderBy("y").toPandas().to_numpy(float) for d in (a, b))
    assert [n for n, a, b in zip(["y", *names], x.T, y.T) if not np.allclose(a, b)] == []


def test_table_report(spark):
    rows = [(k, f"id{k}", str(k), "n/a", 1, "ab"[k % 2]) for k in range(100)]
    df = spark.createDataFrame(rows, "k int, name string, number string, empty string, same int, kind string")
    told = enc.table_report(df)
    assert told == {"k": "keep", "name": "drop: identifier", "number": "cast: double", "empty": "drop: empty", "same": "drop: constant", "kind": "keep"}
    assert enc.clean_table(df).dtypes == [("k", "int"), ("number", "double"), ("kind", "string")]


def test_packed_passes_equal_brute_force(spark):
    rng = np.random.default_rng(8)
    rows = [(None if k % 9 == 0 else float(rng.integers(0, 30)), float(k % 2), float(rng.normal()) if k % 5 else float("nan"), float(rng.normal())) for k in range(400)]
    df = spark.createDataFrame(rows, "a double, b double, c double, y double").repartition(3)
    names = ["a", "b", "c"]
    edges = [[float(e) for e in range(2, 30, 2)], [0.0], [-0.5, 0.5]]
    table = models.binned(df, names, edges, ["y"]).toPandas()
    bins = table[["b0", "b1", "b2"]].to_numpy()
    packing = models.Packing([len(e) + 2 for e in edges])
    wide = df.select("y", *[df[c].alias(f"x{i}") for i, c in enumerate(names)])
    blocks = models.gradient_blocks(wide, packing, edges, 1.5)
    tree = [(0, 6, 1, 2, 0.0, False), (-1, 0, 0, 0, -1.0, True), (2, 1, 3, 4, 0.0, True), (-1, 0, 0, 0, 2.0, True), (-1, 0, 0, 0, 3.0, True)]
    low, right = (bins[:, 0] <= 6) & (bins[:, 0] > 0), bins[:, 2] <= 1
    leaf = np.where(low, 1, np.where(right, 3, 4))
    g = 1.5 - table["y"].to_numpy() + np.array([0, -1.0, 0, 2.0, 3.0])[leaf]
    for moved, trees in ((blocks, [tree]), (models.moved_on(blocks, packing, [tree]), [])):
        got = models.histograms(moved, packing, 17, trees, tree, [(1, None), (4, (1, 1, True, True))])
        for h, mine in zip(got, (leaf == 1, (leaf == 4) & (bins[:, 1] <= 1))):
            for f in range(3):
                assert np.allclose(h[f, :, 0], np.bincount(bins[mine, f], g[mine], 17)) and (h[f, :, 1] == np.bincount(bins[mine, f], minlength=17)).all()


def test_small_listing_uses_every_core(spark, tiny):
    from weftline.workloads import listing as lst

    assert lst.listing(spark, tiny, ["price"]).rdd.getNumPartitions() == spark.sparkContext.defaultParallelism


def test_row_kernel_skips_zeros_alone(spark):
    rows = [(float(k % 3 == 0), float(k % 5 == 0), float(k)) for k in range(60)]
    df = spark.createDataFrame(rows, "a double, b double, y double").coalesce(1)
    z = np.column_stack([np.ones(60), rows])
    assert np.allclose(models.moments_by_rows(df.selectExpr("0 AS _by", "*"), np.zeros(3))[0], z.T @ z)
    bad = spark.createDataFrame([(0.0, float("inf"), 1.0)], "a double, b double, y double").selectExpr("0 AS _by", "*")
    assert np.isnan(models.moments_by_rows(bad, np.zeros(3))[0][1, 2])


def test_few_values_need_no_sketch(spark, monkeypatch):
    df = spark.createDataFrame([(float(i % 7), float("nan") if i == 3 else float(i % 4)) for i in range(50)], "a double, b double")
    want = order.exact_quantiles(df, ["a", "b"])

    def sketch(*_):
        raise AssertionError("a sketch of a column of few values")

    monkeypatch.setattr(order.F, "percentile_approx", sketch)
    monkeypatch.setattr(order.F, "percentile", sketch)
    assert order.exact_quantiles(df, ["a", "b"]) == want == {"a": 3.0, "b": 1.0}
    e = {"kind": "numeric", "cols": ["a"], "impute": "median"}
    assert enc.fit_all(df, [e], "true", "b")[enc.key_of(e)]["a"][0] == 3.0


def test_many_flags_are_kept_as_bits(spark):
    df = spark.createDataFrame([(chr(97 + i % 26) + str(i % 3), float(i)) for i in range(200)], "c string, y double").repartition(3)
    hot = [{"kind": "onehot", "cols": ["c"], "drop_first": False}]
    out, names = enc.apply_all(df, hot, enc.fit_all(df, hot, "true", "y"), ["y"], "true")
    kept, widened = enc.narrowed(out)
    assert len(names) == 78 and len(kept.columns) == 3
    back = widened(kept)
    assert back.dtypes == out.dtypes and sorted(back.collect()) == sorted(out.collect())
    assert all(f.metadata == {enc.FLAG: True} for f in back.schema if f.name in names)


def test_interpreted_steps_take_distinct_values(spark, monkeypatch):
    calls = spark.sparkContext.accumulator(0)
    own = enc.row_onehot

    def counted(*a):
        calls.add(1)
        return own(*a)

    monkeypatch.setattr(enc, "row_onehot", counted)
    df = spark.createDataFrame([([" x ", "y", None, "N/A"][i % 4], float(i)) for i in range(4000)], "c string, y double").coalesce(1)
    hot = [{"kind": "onehot", "cols": ["c"], "drop_first": False}]
    states = enc.fit_all(df, hot, "true", "y")
    (rows, names), (want, _) = (f(df, hot, states, ["y"], "true") for f in (enc.apply_rows, enc.apply_all))
    assert sorted(rows.select("y", *names).collect()) == sorted(want.select("y", *names).collect())
    assert calls.value <= 4


def test_edges_are_quantiles_of_counted_values(spark, monkeypatch):
    rng = np.random.default_rng(5)
    rows = [(float(rng.integers(0, 9)), None if k % 3 else float(rng.normal()), None) for k in range(500)]
    df = spark.createDataFrame(rows, "a double, b double, empty double").repartition(4)
    shares = [k / 8 for k in range(1, 8)]
    sorted_ = [np.sort([r[k] for r in rows if r[k] is not None]) for k in (0, 1)]
    want = [sorted({float(x[int(np.ceil(s * len(x))) - 1]) for s in shares}) for x in sorted_] + [[]]
    sketch = models.F.percentile_approx
    monkeypatch.setattr(models.F, "percentile_approx", None)
    assert models.bin_edges(df, ["a", "b", "empty"], 8) == want
    monkeypatch.setattr(models.F, "percentile_approx", sketch)
    monkeypatch.setattr(models, "COUNTED_VALUES", 20)  # b takes a sketch now, which is exact for so few rows
    assert models.bin_edges(df, ["a", "b", "empty"], 8) == want


def test_small_parts_need_no_round(spark, monkeypatch):
    df = spark.createDataFrame([(0, np.array([float(k)]).tobytes()) for k in range(20)], "b int, m binary").repartition(20)
    rounds, own = [], type(df).repartition
    monkeypatch.setattr(type(df), "repartition", lambda self, *a: rounds.append(a) or own(self, *a))
    assert merge.summed(df, 20, 8.0)[0] == [190.0] and not rounds
    assert merge.summed(df, 1000)[0] == [190.0] and rounds == [(31,), (5,)]


def test_gram_of_few_strings_is_one_part(spark, monkeypatch):
    parts, own = [], enc.summed
    monkeypatch.setattr(enc, "summed", lambda df, *a: parts.append(df.count()) or own(df, *a))
    rows = [(["red ring", "hot bolt", None, "blue ring"][i % 4], float(i)) for i in range(60)]
    df = spark.createDataFrame(rows, "c string, y double").repartition(4)
    both = [{"kind": "text", "cols": ["c"], "n_components": n} for n in (1, 2)]
    states = enc.fit_all(df, both, "true", "y")
    assert parts == [1]  # for both encoders together
    one, two = (states[enc.key_of(e)]["c"] for e in both)
    x = enc.tfidf([r[0] for r in rows if r[0]], two["idf"], both[0])
    values = np.linalg.eigvalsh(x.T @ x)[::-1][:2]
    assert one["idf"] == two["idf"] and np.allclose(two["v"].T @ x.T @ x @ two["v"], np.diag(values)) and np.allclose(one["v"], two["v"][:, :1])


def test_flags_kept_as_bits_stay_so(spark, monkeypatch):
    df = spark.createDataFrame([(chr(97 + i * i % 26) + str(i % 3), float(i % 17), float(i % 5), i % 4) for i in range(400)], "c string, a double, y double, fold int").repartition(3)
    encoders = [{"kind": "numeric", "cols": ["a"]}, {"kind": "onehot", "cols": ["c"]}]
    plain, names = enc.apply_all(df, encoders, enc.fit_all(df, encoders, "true", "y"), ["y", "fold"], "true")
    kept, widened = enc.narrowed(plain)
    back, wanted = enc.filtered(widened(kept), "fold < 3"), plain.filter("fold < 3")
    sent, own = [], type(df).mapInArrow
    monkeypatch.setattr(type(df), "mapInArrow", lambda self, *a: sent.append(len(self.columns)) or own(self, *a))
    got = [models.moments(back, names, "y", "fold"), models.bin_edges(back, names, 8), models.boost(back, names, "y", trees=2)]
    assert len(names) > 30 and max(sent) <= 4
    want = [models.moments(wanted, names, "y", "fold"), models.bin_edges(wanted, names, 8), models.boost(wanted, names, "y", trees=2)]
    assert set(got[0]) == set(want[0]) == {0, 1, 2} and all(np.allclose(got[0][k], want[0][k]) for k in want[0])
    assert got[1] == want[1] and got[2]["edges"] == want[2]["edges"]
    a, b = (d.select(models.prediction(m, names).alias("p")).orderBy("p").toPandas()["p"] for d, m in ((back, got[2]), (wanted, want[2])))
    assert np.allclose(a, b)
    assert enc.packed_form(enc.filtered(widened(kept), f"{names[-1]} = 1")) is None
