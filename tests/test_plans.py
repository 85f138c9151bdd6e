"""Plans: recording, fusion, rewrites, lowering, selection and schedules, without Spark."""

import pytest

from weftline.plans import rewrite, schedule, select
from weftline.plans.ir import Dag, Node, validate_acyclic
from weftline.plans.lowering import lower
from weftline.plans.pipeline import Pipeline, PipelineBatch, choose, expand_variants, fuse, parse_spec, to_spec
from weftline.runtime.cache import mark_candidates
from weftline.runtime.measures import changed_line_ratio
from weftline.search.loop import halving_plan
from weftline.workloads import listing as lst


def counts(dag):
    return {op: dag.count(op) for op in ("READ", "FIT_PREP", "APPLY_PREP", "MOMENTS", "SOLVE", "APPLY_MODEL", "SCORE")} | {"all": dag.count()}


def test_fused_four_node_counts():
    raw = fuse(lst.fused_four())
    assert raw.count() == 24
    assert counts(lower(raw)) == {"READ": 4, "FIT_PREP": 4, "APPLY_PREP": 4, "MOMENTS": 4, "SOLVE": 4, "APPLY_MODEL": 4, "SCORE": 4, "all": 28}
    assert counts(rewrite.cse(lower(raw))) == {"READ": 1, "FIT_PREP": 2, "APPLY_PREP": 2, "MOMENTS": 2, "SOLVE": 4, "APPLY_MODEL": 4, "SCORE": 4, "all": 19}
    merged = lower(rewrite.cse(rewrite.merge_fits(raw)))
    assert counts(merged)["FIT_PREP"] == 1 and counts(merged)["all"] == 18


def test_eight_preparations_become_two():
    dag = rewrite.cse(fuse(lst.iteration_one()))
    assert len(dag.sinks) == 8 and dag.count("APPLY_PREP") == 2


def test_rewrites_reach_a_fixpoint():
    dag, trace = rewrite.optimize_logical(fuse(lst.fused_four()))
    again, more = rewrite.optimize_logical(dag)
    assert trace and not more and again.sinks == dag.sinks


def test_grid_and_folds_are_unrolled():
    model = {"kind": "trees", "growth": "level"}
    p = Pipeline.read("listing").prepare(lst.SCALED, lst.TRAIN, lst.TARGET)
    cv = rewrite.cse(lower(Dag({"q": p.cross_validate(model, lst.TRAIN, lst.TARGET, folds=3).node})))
    assert cv.count("FIT_TREES") == cv.count("SCORE") == 3
    grid = rewrite.cse(lower(Dag({"q": p.grid_search([{"kind": "ridge", "alpha": a} for a in (1.0, 2.0)], lst.TRAIN, lst.TARGET).node})))
    assert (grid.count("SOLVE"), grid.count("MOMENTS"), grid.count("AVERAGE")) == (8, 1, 2)


def test_filters_stay_above_fits():
    p = Pipeline.read("listing").prepare(lst.SCALED, lst.TRAIN, lst.TARGET).select("bucket = 8")
    sink = rewrite.push_filters(Dag({"q": p.node})).sinks["q"]
    assert sink.op == "APPLY_PREP" and sink.inputs[0].op == "FILTER" and sink.inputs[1].inputs[0].op == "READ"


def test_filters_stay_above_what_they_read():
    p = Pipeline.read("part").map(x="p_size + 1").select("x > 3")
    assert rewrite.push_filters(Dag({"q": p.node})).sinks["q"].op == "FILTER"


def test_no_truth_values_and_no_circles():
    with pytest.raises(TypeError):
        bool(Node("READ"))
    with pytest.raises(ValueError):
        validate_acyclic([("a", "b"), ("b", "c"), ("c", "a")])
    validate_acyclic([("a", "b"), ("a", "c"), ("b", "c")])


def test_random_steps_need_seeds_to_be_kept():
    fn = lambda df: df
    read = Pipeline.read("part")
    assert read.call(fn).node.cacheable and read.call(fn, deterministic=False, seed=1).node.cacheable
    unseeded = read.call(fn, deterministic=False)
    assert not unseeded.node.cacheable and not unseeded.map(x="1").node.cacheable


def test_functions_are_told_apart_by_code_and_closure():
    def adder(k):
        return lambda x: x + k

    a, b, c = (Node("UDF", {"fn": adder(k)}) for k in (1, 1, 2))
    assert a.key == b.key != c.key


def test_specs_round_trip():
    for p in lst.iteration_one().pipelines:
        assert parse_spec(to_spec(p)).node.key == p.node.key


def test_variants():
    stages = [choose("a", {"x": lambda p: p.map(a="1"), "y": lambda p: p.map(a="2")}), choose("b", {"z": lambda p: p})]
    assert [p.name for p in expand_variants(Pipeline.read("t"), stages)] == ["x/z", "y/z"]
    with pytest.raises(ValueError):
        PipelineBatch((Pipeline.read("t"), Pipeline.read("t")))


SIZES = {"dict": "CASE p_size WHEN 1 THEN 'one' WHEN 2 THEN 'two' END"}
NAMES = {1: "one", 2: "two"}


def test_traced_functions():
    assert rewrite.traced(lambda a, b: a * b + 1) == "((a * b) + 1)"
    assert rewrite.traced(lambda a: a if a > 2 else 0) == "CASE WHEN (a > 2) THEN a ELSE 0 END"
    assert rewrite.traced(lambda p_size: NAMES[p_size]) == SIZES["dict"]
    assert rewrite.traced(lambda a: a.strip()) is None
    k = 7
    assert rewrite.traced(lambda x: x * k, ["p_size"]) == "(p_size * 7)"
    assert rewrite.traced(lambda x, y: x - y, ["a", "odd name"]) == "(a - `odd name`)"
    two = (lambda x: x + 1, lambda x: x + 2)
    assert [rewrite.traced(f, ["c"]) for f in two] == ["(c + 1)", "(c + 2)"]
    assert rewrite.traced(lambda x: x + undefined_name, ["c"]) is None  # noqa: F821


def test_choice_follows_budget_cache_and_registry():
    dag = lower(rewrite.cse(fuse(lst.fused_four())))
    sources, registry = {"listing": select.Meta(1e7, 18)}, select.default_registry()
    bound, seconds = select.select_impls(dag, registry, sources, 4e9)
    assert {i.backend for i in bound.values()} <= {"catalyst", "arrow"} and seconds > 0
    with pytest.raises(MemoryError):
        select.select_impls(dag, registry, sources, 10)
    prep = next(n.key for n in dag.nodes() if n.op == "APPLY_PREP")
    cached, less = select.select_impls(dag, registry, sources, 4e9, cached={prep})
    assert cached[prep].name == "reload"
    registry.register("APPLY_PREP", select.Implementation("new", "catalyst", 0.0, 0.0))
    assert select.select_impls(dag, registry, sources, 4e9)[0][prep].name == "new"
    heuristic, _ = select.select_impls(dag, registry, sources, 4e9, policy="heuristic")
    assert heuristic.keys() == {n.key for n in dag.nodes()} and select.count_boundaries(dag, heuristic) >= 0


def test_samples_calibrate_costs():
    registry = select.default_registry()
    registry.calibrate("MOMENTS", "arrow_blocks", [(select.Meta(100, 10), 1.0), (select.Meta(300, 10), 2.0)], safety=1.0)
    found = next(i for i in registry.entries["MOMENTS"] if i.name == "arrow_blocks")
    assert found.fixed == pytest.approx(0.5) and found.per_value == pytest.approx(0.0005)


@pytest.mark.parametrize("policy", ["cost", "heuristic"])
def test_schedules_keep_the_budget_and_the_order(policy):
    dag = lower(rewrite.cse(fuse(lst.iteration_one())))
    estimates = {n.key: select.CostEstimate(1.0, 100.0, 1e6, 10) for n in dag.nodes()}
    plan = schedule.plan_schedule(dag, estimates, 350.0, 8, policy)
    assert plan.peak_bytes <= 350 and set(plan.order) == set(estimates)
    place = {k: i for i, k in enumerate(plan.order)}
    assert all(place[u.key] < place[n.key] for n in dag.nodes() for u in n.inputs)
    serial = schedule.simulate(dag, estimates, 1, 350.0, 8)
    assert policy != "cost" or plan.makespan <= serial.makespan
    assert all(t * plan.width <= max(8, plan.width) for t in plan.tasks.values())
    with pytest.raises(MemoryError):
        schedule.plan_schedule(dag, estimates, 50.0, 8, policy)


def test_candidates_for_the_cache():
    dag = rewrite.cse(fuse(lst.iteration_one()))
    preps = [n.key for n in dag.nodes() if n.op == "APPLY_PREP"]
    assert mark_candidates(dag, {preps[0]: 5.0, preps[1]: 1.0}, {k: 1e6 for k in preps}) == preps
    assert mark_candidates(dag, {preps[0]: 5.0}, {}, policy="greedy", threshold=2.0) == preps[:1]


def test_measures_of_change_and_halving():
    assert changed_line_ratio("a\nb\nc", "a\nx\nc") == pytest.approx(2 / 6)
    assert changed_line_ratio("a", "a") == 0
    assert halving_plan(9, 3, 1000, 10**6) == [(9, 1000), (3, 3000), (1, 9000)]
    assert halving_plan(9, 3, 1000, 2000) == [(9, 1000), (3, 2000)]
