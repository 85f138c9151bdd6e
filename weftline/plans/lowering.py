"""From logical steps to physical ones: composite steps become explicit nodes."""

from __future__ import annotations

from collections.abc import Callable

from .ir import Dag, Node

ADDITIVE, CLASSIFIERS = ("ridge", "elastic_net"), ("logistic", "perceptron")


def lower_model(n: Node) -> Node:
    """Linear models to moments and a solve, trees to bins and growth."""
    model, train, target = n.params["model"], n.params["train"], n.params["target"]
    if model["kind"] in ADDITIVE:
        sums = Node("MOMENTS", {"rows": train, "target": target, "by": None}, n.inputs)
        return Node("SOLVE", {"model": model, "leave_out": None, "rows": train, "target": target}, (*n.inputs, sums))
    if model["kind"] in CLASSIFIERS:
        return Node("FIT_CLASSIFIER", {"model": model, "train": train, "target": target}, n.inputs)
    return Node("FIT_TREES", {"model": model, "train": train, "target": target}, n.inputs)


def lower_cross_validation(n: Node) -> Node:
    """Folds as branches: with additive statistics, training sums are totals less the fold's."""
    p, data = n.params, n.inputs[0]
    branches = []
    for f in range(p["folds"]):
        if p["model"]["kind"] in ADDITIVE and p["metric"] == "rmse":
            sums = Node("MOMENTS", {"rows": p["train"], "target": p["target"], "by": p["fold"]}, (data,))
            solved = Node("SOLVE", {"model": p["model"], "leave_out": f}, (data, sums))
            branches.append(Node("SCORE_MOMENTS", {"fold": f}, (solved, sums)))
        else:
            kept, held = f"({p['train']}) AND {p['fold']} <> {f}", f"({p['train']}) AND {p['fold']} = {f}"
            fit = Node("FIT_MODEL", {"model": p["model"], "train": kept, "target": p["target"]}, (data,))
            applied = Node("APPLY_MODEL", {"model": p["model"], "target": p["target"]}, (data, fit))
            branches.append(Node("SCORE", {"metric": p["metric"], "rows": held, "target": p["target"]}, (applied,)))
    return Node("AVERAGE", {"labels": [str(f) for f in range(p["folds"])]}, tuple(branches))


def lower_grid(n: Node) -> Node:
    """Each setting is a cross-validation of its own; they share everything before it."""
    rest = {k: v for k, v in n.params.items() if k != "grid"}
    return Node("BEST", {"labels": [str(k) for k in range(len(n.params["grid"]))], "settings": n.params["grid"]}, tuple(Node("CROSS_VALIDATE", rest | {"model": m}, n.inputs) for m in n.params["grid"]))


def lower_auto_encoder(n: Node, route: Callable[[Node], list[dict]]) -> Node:
    """Cleaner, one-hot, string and date encoders, as the profile of the columns has it."""
    prep = {"encoders": route(n), "carry": n.params["carry"]}
    shared = {"prep": prep, "train": n.params["train"], "target": n.params["target"]}
    return Node("APPLY_PREP", shared, (n.inputs[0], Node("FIT_PREP", shared, n.inputs)))


def fuse_rowwise(dag: Dag) -> Dag:
    """Adjacent assignments and projections as one step."""
    from .rewrite import collapse_assignments

    return collapse_assignments(dag)


def lower(dag: Dag, route: Callable[[Node], list[dict]] | None = None, max_rounds: int = 8) -> Dag:
    """Passes until no composite step is left."""
    rules: dict[str, Callable[[Node], Node]] = {"FIT_MODEL": lower_model, "CROSS_VALIDATE": lower_cross_validation, "GRID_SEARCH": lower_grid}
    if route is not None:
        rules["AUTO_PREP"] = lambda n: lower_auto_encoder(n, route)
    for _ in range(max_rounds):
        new = dag.mapped(lambda n: rules[n.op](n) if n.op in rules else n)
        if new.sinks == dag.sinks:
            return new
        dag = new
    return dag
