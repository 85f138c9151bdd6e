"""Estimators against NumPy, and the runners' agreement."""

import threading
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pytest

from weftline.operators import encoders as enc
from weftline.operators import models, profile
from weftline.plans.pipeline import fuse
from weftline.runtime.cache import ReuseCache
from weftline.runtime.executor import ABLATION, Executor, OptFlags, run_optimized, run_thread_parallel
from weftline.workloads import listing as lst


@pytest.fixture(scope="module")
def numbers(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 3))
    y = x @ [3.0, -2.0, 0.0] + 5 + rng.normal(size=300) * 0.1
    rows = [(float(a), float(b), float(c), float(d), i % 4) for i, ((a, b, c), d) in enumerate(zip(x, y))]
    return spark.createDataFrame(rows, "a double, b double, c double, y double, fold int").repartition(3), x, y


def edit_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


@pytest.mark.parametrize("cut_values", [1000, 7])
def test_match_everywhere_misses_nothing(spark, cut_values):
    rng = np.random.default_rng(2)
    values = {"small ring", "large ring", "", "🙂é", "é🙂"} | {"".join(rng.choice(list("abé "), rng.integers(1, 9))) for _ in range(60)}
    df = spark.createDataFrame([(v,) for v in [*values, "small ring", None]], "name string")
    for threshold in (0.4, 0.5, 0.8):
        near = {(a, b): round(1 - edit_distance(a, b) / max(len(a), len(b)), 6) for a in values for b in values if a.encode() < b.encode()}
        got = profile.match_everywhere(df, df, "name", threshold, cut_values).collect()
        assert len(got) == len({(r[0], r[1]) for r in got})
        assert {(r[0], r[1]): r[2] for r in got} == {p: s for p, s in near.items() if s >= threshold}
    assert near["large ring", "small ring"] >= 0.5


def test_moments_and_ridge(numbers):
    df, x, y = numbers
    m = models.moments(df, ["a", "b", "c"], "y", "fold")
    z = np.column_stack([np.ones(300), x, y])
    assert np.allclose(sum(m.values()), z.T @ z) and np.allclose(m[1], z[1::4].T @ z[1::4])
    assert np.allclose(models.moments(df, ["a", "b", "c"], "y", kernel="rows")[0], z.T @ z)
    w = models.solve_ridge(sum(m.values()), 2.0)
    xc, yc = x - x.mean(0), y - y.mean()
    assert np.allclose(w["w"], np.linalg.solve(xc.T @ xc + 2 * np.eye(3), xc.T @ yc))


def test_arrow_blocks_agree(numbers, monkeypatch):
    df, x, y = numbers
    monkeypatch.setattr(models, "EXPRESSION_COLUMNS", 0)
    z = np.column_stack([np.ones(300), x, y])
    assert np.allclose(models.moments(df, ["a", "b", "c"], "y")[0], z.T @ z)


def test_elastic_net_meets_its_conditions(numbers):
    _, x, y = numbers
    z = np.column_stack([np.ones(300), x, y])
    alpha, rho = 0.5, 0.7
    w = np.array(models.solve_elastic_net(z.T @ z, alpha, rho)["w"])
    xc, yc = x - x.mean(0), y - y.mean()
    gradient = xc.T @ (xc @ w - yc) / 300 + alpha * (1 - rho) * w
    assert all(abs(g + alpha * rho * np.sign(v)) < 1e-6 if v else abs(g) <= alpha * rho + 1e-6 for g, v in zip(gradient, w))
    assert w[2] == 0


def test_singular_moments():
    x = np.ones((10, 2))
    z = np.column_stack([np.ones(10), x, np.arange(10.0)])
    assert np.isfinite(models.solve_ridge(z.T @ z, 0.0)["w"]).all()


def test_best_split_by_brute_force():
    rng = np.random.default_rng(2)
    h = np.dstack([rng.normal(size=(3, 5)), rng.integers(1, 9, (3, 5))])
    h[1:, :, 1] *= h[0, :, 1].sum() / h[1:, :, 1].sum(1, keepdims=True)
    h[1:, :, 0] *= (h[0, :, 0].sum() / h[1:, :, 0].sum(1))[:, None]
    gain, f, b = models.best_split(h, 1.0)
    g, n = h[0, :, 0].sum(), h[0, :, 1].sum()
    told = lambda i, k: 0.5 * (h[i, : k + 1, 0].sum() ** 2 / (h[i, : k + 1, 1].sum() + 1) + (g - h[i, : k + 1, 0].sum()) ** 2 / (n - h[i, : k + 1, 1].sum() + 1) - g**2 / (n + 1))
    assert gain == pytest.approx(max(told(i, k) for i in range(3) for k in range(4))) == pytest.approx(told(f, b))


@pytest.mark.parametrize("growth", ["level", "leaf"])
def test_trees_learn(numbers, growth):
    df, x, y = numbers
    model = models.boost(df, ["a", "b", "c"], "y", growth=growth, trees=5, eta=0.5)
    got = df.select(models.prediction(model, ["a", "b", "c"]).alias("p"), "y").toPandas()
    assert ((got["p"] - got["y"]) ** 2).mean() < 0.25 * y.var()


def test_sketch_keeps_its_bound(spark):
    x = np.random.default_rng(1).normal(size=(200, 12)) * np.arange(1, 13)
    df = spark.createDataFrame([(list(map(float, r)),) for r in x], "e array<double>").repartition(4)
    b = models.frequent_directions(df, "e", 8)
    assert np.linalg.norm(x.T @ x - b.T @ b, 2) <= (x**2).sum() / 8 + 1e-6
    exact, _ = models.truncated_svd(df, "e", 3)
    assert np.allclose(exact, np.linalg.svd(x, compute_uv=False)[:3])


def test_encoders_on_six_rows(spark):
    rows = [(1.0, "a", 10, 0), (None, "b", 20, 0), (3.0, " N/A ", 30, 1), (5.0, "a", 40, 1), (None, None, 50, 9), (7.0, "new", 60, 9)]
    df = spark.createDataFrame(rows, "x double, c string, y int, fold int").repartition(2)
    num, hot = {"kind": "numeric", "cols": ["x"]}, {"kind": "onehot", "cols": ["c"], "drop_first": False}
    tgt = {"kind": "target", "cols": ["c"], "smoothing": 0.0}
    states = enc.fit_all(df, [num, hot, tgt], "fold < 9", "y")
    assert states[enc.key_of(num)]["x"] == pytest.approx((3.0, 3.0, 2**0.5))
    assert states[enc.key_of(hot)]["c"] == (["a", "b"], [])
    got = {r["y"]: r for r in enc.apply_all(df, [num, hot, tgt], states, ["y"], "fold < 9")[0].collect()}
    assert (got[60]["f_c_0"], got[60]["f_c_1"]) == (0, 0) and got[60]["f_c_mean"] == pytest.approx(25.0)
    assert got[10]["f_c_mean"] == pytest.approx(25.0) and got[20]["f_x"] == 0


def test_constant_and_empty_columns(spark):
    df = spark.createDataFrame([(2.0, None, 1), (2.0, None, 2)], "k double, e double, y int")
    e = {"kind": "numeric", "cols": ["k", "e"]}
    out = enc.apply_all(df, [e], enc.fit_all(df, [e], "true", "y"), ["y"], "true")[0].collect()
    assert all(r["f_k"] == 0 and r["f_e"] == 0 for r in out)


def test_auc_with_ties(spark):
    df = spark.createDataFrame([(0, 1.0), (1, 1.0), (0, 0.0), (1, 2.0)], "y int, s double")
    assert models.auc(df, "y", "s").first()[0] == pytest.approx(0.875)


def test_task_kinds_and_errors(spark):
    df = spark.createDataFrame([(i, float(i), str(i % 2)) for i in range(50)], "id int, v double, c string")
    assert [profile.infer_task(df, c) for c in ("v", "c", "id")] == ["regression", "classification", "regression"]
    assert profile.detect_errors(df, {"big": "v < 48"}, ["id"]).count() == 2


def test_every_mode_gives_the_same_scores(spark, tiny):
    got = {}
    for step in ("logical", "selection", "parallel", "full"):
        flags = ABLATION[step]
        run = Executor(spark, tiny, flags, ReuseCache(spark, tiny) if flags.reuse else None).run(fuse(lst.fused_four()))
        got[step] = {t["pipeline_id"]: t["value"] for t in run.trials}
        assert run.reads == 1 and all(t["status"] == "ok" for t in run.trials)
    assert all(v == pytest.approx(got["logical"], rel=1e-9) for v in got.values())


def test_second_run_is_served_from_the_cache(spark, tiny):
    cache = ReuseCache(spark, tiny)
    first = run_optimized(spark, tiny, lst.fused_four(), cache=cache)
    before = dict(cache.stats)
    again = run_optimized(spark, tiny, lst.fused_four(), cache=cache)
    assert cache.stats["stored"] == before["stored"] == 2 and cache.stats["hits"] > before["hits"]
    assert {t["pipeline_id"]: t["value"] for t in again.trials} == pytest.approx({t["pipeline_id"]: t["value"] for t in first.trials})


def test_failures_stay_with_their_pipeline(spark, tiny):
    run = run_optimized(spark, tiny, lst.infeasible(), flags=ABLATION["parallel"])
    assert {t["pipeline_id"]: t["status"] for t in run.trials} == {"scaled/ridge": "ok", "wide/ridge": "infeasible", "failing/ridge": "failed: ValueError"}


def test_entry_and_registry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 4
    assert set(e.oracle_sql()) <= set(e.queries())


def test_replan_stays_with_its_operator(spark, tiny):
    """Unshared pipelines in threads: a slow MOMENTS by rows mustn't hand its code to other operators' python_rows."""
    ex = Executor(spark, tiny, OptFlags(False, False, True, False))
    dag, _ = ex.plan(fuse(lst.fused_four()))
    ex.bind(dag)
    nodes = {n.key: n for n in dag.nodes()}
    slow = next(n for n in nodes.values() if n.op == "MOMENTS")
    before = {k: i.run for k, i in ex.bound.items()}
    ex.observed[slow.key] = 1e4
    ex._surprised(slow)
    assert ex.replans == 1 and {ex.bound[k].name for k, n in nodes.items() if n.op in ("APPLY_PREP", "MOMENTS")} == {"python_rows"}
    assert {k: i.run for k, i in ex.bound.items()} == before


def test_unshared_pipelines_fit_once_each(spark, tiny, monkeypatch):
    fits, own = [], Executor._fit_prep
    monkeypatch.setattr(Executor, "_fit_prep", lambda ex, p, df: fits.append(1) or own(ex, p, df))
    run = run_thread_parallel(spark, tiny, lst.fused_four())
    assert len(fits) == 4 and all(t["status"] == "ok" for t in run.trials)


def test_shared_listing_is_joined_once(spark, tiny):
    ex = Executor(spark, tiny, OptFlags(reuse=False))
    dag, _ = ex.plan(fuse(lst.fused_four()))
    ex.bind(dag)
    read = next(n for n in dag.nodes() if n.op == "READ")
    frame = ex._value(read, "read", dag.consumers())
    try:
        assert frame.is_cached
    finally:
        frame.unpersist()


def test_few_states_are_broadcast(spark, monkeypatch):
    rows = [(["red ring", "hot bolt", None, "blue ring"][i % 4], float(i), i % 3) for i in range(60)]
    df = spark.createDataFrame(rows, "c string, y double, fold int").repartition(3)
    both = [{"kind": "text", "cols": ["c"], "n_components": 2}, {"kind": "target", "cols": ["c"], "fold": "fold"}]

    def applied():
        return enc.apply_all(df, both, enc.fit_all(df, both, "y < 50", "y"), ["y"], "y < 50")[0]

    few = applied()
    assert few._jdf.queryExecution().optimizedPlan().toString().count("rightHint=(strategy=broadcast)") == 3
    want = {r["y"]: r for r in few.collect()}
    monkeypatch.setattr(enc, "LOCAL_ROWS", 1)
    many = {r["y"]: r for r in applied().collect()}
    assert set(want) == set(many) and all(np.allclose(list(want[y]), list(many[y])) for y in want)


def test_zeros_and_ones_are_kept_as_bytes(spark):
    df = spark.createDataFrame([("abac"[i % 4], float(i)) for i in range(40)], "c string, y double").repartition(3)
    hot = [{"kind": "onehot", "cols": ["c"], "drop_first": False, "min_count": 1}]
    out, names = enc.apply_all(df, hot, enc.fit_all(df, hot, "true", "y"), ["y"], "true")
    kept, widened = enc.narrowed(out)
    assert [t for c, t in kept.dtypes if c in names] == ["tinyint"] * 3
    back = widened(kept)
    assert sorted(back.collect()) == sorted(out.collect()) and back.dtypes == out.dtypes
    plain = out.select(*[out[c].cast("string").cast("double").alias(c) for c in names])
    assert models.bin_edges(back, names, 16) == models.bin_edges(plain, names, 16)


def test_unshared_pipelines_keep_their_own_frames(spark, tiny, monkeypatch):
    kept, own = [], enc.narrowed
    monkeypatch.setattr(enc, "narrowed", lambda df: kept.append(df) or own(df))
    run = run_thread_parallel(spark, tiny, lst.fused_four())
    assert len(kept) == 4 and all(t["status"] == "ok" for t in run.trials)


def test_fits_together_share_bins_and_passes(spark, monkeypatch):
    rng = np.random.default_rng(3)
    rows = [(float(rng.integers(0, 40)), None if k % 7 == 0 else float(rng.normal()), float(rng.normal() + (k % 5))) for k in range(600)]
    df = spark.createDataFrame(rows, "a double, b double, y double").repartition(3)
    settings = [{"growth": "level", "trees": 5, "depth": d} for d in (2, 3)] + [{"growth": "leaf", "trees": 10, "leaves": n} for n in (4, 20)]
    passes, own = [], models.histograms_of_fits
    monkeypatch.setattr(models, "histograms_of_fits", lambda *a: passes.append(len(a[3])) or own(*a))
    alone = [models.boost(df, ["a", "b"], "y", **s) for s in settings]
    before, asked = len(passes), sum(passes)
    passes.clear()
    binned = models.Binned(df, ["a", "b"], "y", 16)
    entered = threading.Barrier(len(settings))
    enter = models.Binned.__enter__
    monkeypatch.setattr(models.Binned, "__enter__", lambda self: enter(self) and (entered.wait(60), self)[1])
    with ThreadPoolExecutor(len(settings)) as pool:
        together = list(pool.map(lambda s: models.boost(df, ["a", "b"], "y", **s, shared=binned), settings))
    binned.unpersist()
    assert sum(passes) == asked == before and len(passes) < 0.75 * before
    for one, same in zip(alone, together):
        assert one["edges"] == same["edges"]
        a, b = (df.select(models.prediction(m, ["a", "b"])).toPandas().to_numpy() for m in (one, same))
        assert np.allclose(a, b)


def test_a_failed_pass_reaches_every_fit(spark, monkeypatch):
    df = spark.createDataFrame([(float(i), float(i % 3)) for i in range(30)], "a double, y double")
    binned = models.Binned(df, ["a"], "y", 4)

    def failing(*_):
        raise ValueError("a pass that fails")

    monkeypatch.setattr(models, "histograms_of_fits", failing)
    with ThreadPoolExecutor(2) as pool:
        fits = [pool.submit(models.boost, df, ["a"], "y", shared=binned) for _ in range(2)]
        assert all(isinstance(f.exception(60), ValueError) for f in fits)
    binned.unpersist()


def test_trees_of_one_preparation_share_their_bins(spark, tiny, monkeypatch):
    made, own = [], models.Binned
    monkeypatch.setattr(models, "Binned", lambda *a: made.append(a) or own(*a))
    trees = {k: lst.MODELS[k] | {"trees": 2} for k in ("trees_level", "trees_leaf")}
    run = run_optimized(spark, tiny, lst.batch({"scaled": lst.SCALED}, trees), flags=OptFlags(reuse=False))
    assert [t["status"] for t in run.trials] == ["ok", "ok"] and len(made) == 1
