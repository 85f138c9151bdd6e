"""Implementations of physical operators, their costs, and the choice among them.

Binding is late: a registry maps an operator to implementations by backend, costs
are linear in rows and columns with constants that samples calibrate, and the
choice minimises time with conversions between backends under a memory bound.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from .ir import Dag, Node

#: Ties go to the left.
PREFERENCE = ("catalyst", "mllib", "arrow", "pickle")
CONVERT_SECONDS_PER_BYTE = {("catalyst", "arrow"): 4e-10, ("arrow", "catalyst"): 4e-10, ("catalyst", "pickle"): 8e-9, ("pickle", "catalyst"): 8e-9, ("arrow", "pickle"): 8e-9, ("pickle", "arrow"): 8e-9}


@dataclass(frozen=True)
class Meta:
    """What is known of a node's output."""

    rows: float
    cols: float
    bytes_per_value: float = 8.0

    @property
    def bytes(self) -> float:
        return self.rows * self.cols * self.bytes_per_value


@dataclass(frozen=True)
class CostEstimate:
    seconds: float
    peak_bytes: float
    out_rows: float
    out_cols: float


@dataclass(frozen=True)
class Implementation:
    """Time is ``fixed + per_value · rows · cols``; memory what an executor or the driver must hold."""

    name: str
    backend: str
    fixed: float = 0.05
    per_value: float = 1e-8
    hidden: float = 0.0
    state_bytes: Callable[[Meta], float] = lambda m: 0.0
    applicable: Callable[[Node, Meta], bool] = lambda n, m: True
    device: str = "cpu"
    fidelity: str = "full"
    #: The code: (executor, parameters, inputs) to the value; None where the executor's only form is meant.
    run: Callable | None = None

    def estimate(self, meta: Meta, out: Meta) -> CostEstimate:
        """Peak: what comes in and goes out and, at worst, hidden copies of what comes in."""
        return CostEstimate(self.fixed + self.per_value * meta.rows * meta.cols, self.state_bytes(meta) + self.hidden * meta.bytes, out.rows, out.cols)


@dataclass
class Registry:
    entries: dict[str, list[Implementation]] = field(default_factory=dict)

    def register(self, op: str, impl: Implementation) -> None:
        self.entries.setdefault(op, []).append(impl)

    def named(self, op: str, name: str) -> Implementation:
        return next(i for i in self.entries[op] if i.name == name)

    def options(self, node: Node, meta: Meta, *, fidelity: str = "full", devices: tuple[str, ...] = ("cpu",)) -> list[Implementation]:
        found = [i for i in self.entries.get(node.op, [Implementation("catalyst", "catalyst")]) if i.device in devices and i.applicable(node, meta)]
        wanted = [i for i in found if i.fidelity == fidelity]
        return wanted or found

    def calibrate(self, op: str, name: str, samples: list[tuple[Meta, float]], safety: float = 1.2) -> None:
        """A line through two or more timed samples replaces the constants."""
        xs, ys = [m.rows * m.cols for m, _ in samples], [s for _, s in samples]
        mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
        slope = max(0.0, sum((x - mx) * (y - my) for x, y in zip(xs, ys)) / max(sum((x - mx) ** 2 for x in xs), 1e-30))
        fresh = lambda i: replace(i, fixed=max(0.0, my - slope * mx) * safety, per_value=slope * safety)
        self.entries[op] = [fresh(i) if i.name == name else i for i in self.entries[op]]


def default_registry() -> Registry:
    """Entries own the code that they name, see ``runtime.kernels``; constants are first guesses that samples replace."""
    from ..runtime import kernels

    out = Registry()
    square = lambda m: 8.0 * m.cols**2
    linear, trees = (lambda n, m: n.params["model"]["kind"] != "trees"), (lambda n, m: True)
    out.register("APPLY_PREP", Implementation("catalyst_expr", "catalyst", 0.01, 2e-9, run=kernels.prep_expressions))
    out.register("APPLY_PREP", Implementation("python_rows", "pickle", 0.3, 4e-7, 1.0, run=kernels.prep_rows))
    out.register("MOMENTS", Implementation("catalyst_agg", "catalyst", 0.1, 2e-8, 0, square, lambda n, m: m.cols <= 8, run=kernels.moments("expressions")))
    out.register("MOMENTS", Implementation("arrow_blocks", "arrow", 0.4, 6e-9, 0.01, square, run=kernels.moments("blocks")))
    out.register("MOMENTS", Implementation("python_rows", "pickle", 0.5, 2e-7, 0.5, square, run=kernels.moments("rows")))
    out.register("SOLVE", Implementation("driver_solve", "arrow", 0.01, 0.0, 0, square, linear, run=kernels.solve_moments))
    out.register("SOLVE", Implementation("mllib_linear", "mllib", 1.0, 3e-8, 0.1, lambda m: 0.0, lambda n, m: linear(n, m) and n.params["leave_out"] is None, run=kernels.solve_mllib))
    out.register("FIT_TREES", Implementation("arrow_histograms", "arrow", 0.5, 3e-8, 0.05, lambda m: 16.0 * m.cols * 64, trees, run=kernels.trees_histograms))
    out.register("FIT_TREES", Implementation("mllib_trees", "mllib", 2.0, 9e-8, 1.0, run=kernels.trees_mllib))
    out.register("FIT_TREES", Implementation("few_trees", "arrow", 0.3, 1.5e-8, 0.05, lambda m: 16.0 * m.cols * 64, trees, fidelity="low", run=kernels.trees_few))
    kind = lambda name: lambda n, m: n.params["model"]["kind"] == name
    out.register("FIT_CLASSIFIER", Implementation("weighted_moments", "arrow", 1.0, 5e-8, 0, square, kind("logistic"), run=kernels.classifier_logistic))
    out.register("FIT_CLASSIFIER", Implementation("mllib_perceptron", "mllib", 3.0, 2e-7, 0.5, lambda m: 0.0, kind("perceptron"), run=kernels.classifier_perceptron))
    out.register("SVD", Implementation("gram", "arrow", 0.3, 1e-8, 0, square, run=kernels.svd("gram")))
    out.register("SVD", Implementation("mllib", "mllib", 1.5, 2e-8, 0, square, run=kernels.svd("mllib")))
    out.register("SVD", Implementation("freq_dir", "arrow", 0.3, 4e-9, 0, lambda m: 8.0 * 40 * m.cols, fidelity="low", run=kernels.svd("freq_dir")))
    out.register("SVD", Implementation("randomized", "arrow", 0.3, 1.1e-8, 0, square, fidelity="low", run=kernels.svd("randomized")))
    out.register("DISTINCT", Implementation("exact", "catalyst", 0.2, 4e-8, run=kernels.distinct(True)))
    out.register("DISTINCT", Implementation("sketch", "catalyst", 0.1, 5e-9, fidelity="low", run=kernels.distinct(False)))
    return out


def estimates_of(dag: Dag, bound: "Binding", metas: dict[str, Meta]) -> dict[str, CostEstimate]:
    """What the bound implementations are expected to take."""
    out = {}
    for n in replace(dag, shared=True).nodes():
        before = metas[n.inputs[0].key] if n.inputs else metas[n.key]
        impl = bound.get(n.key, Implementation("catalyst", "catalyst"))
        out[n.key] = impl.estimate(before, metas[n.key])
    return out


def calibrate_by_sample(registry: Registry, node: Node, meta: Meta, timed: Callable[[Implementation, float], float], fractions: tuple[float, ...] = (0.01, 0.03)) -> dict[str, tuple[float, float]]:
    """Runs every implementation of the node's operator on samples and fits its constants; (fixed, per value) by name."""
    for impl in list(registry.options(node, meta)):
        registry.calibrate(node.op, impl.name, [(replace(meta, rows=meta.rows * f), timed(impl, f)) for f in fractions])
    return {i.name: (i.fixed, i.per_value) for i in registry.options(node, meta)}


def estimate_udf(node: Node, meta: Meta, sampled_ratio: float | None = None) -> CostEstimate:
    """A function over rows or batches keeps their number; another one's output is as a sample has it, at worst double."""
    ratio = 1.0 if node.params["shape"] in ("map", "row") else 2.0 if sampled_ratio is None else sampled_ratio
    rows = meta.rows * ratio
    return CostEstimate(0.3 + 4e-7 * meta.rows * meta.cols, meta.bytes + rows * meta.cols * meta.bytes_per_value, rows, meta.cols)


def features_of(encoders: list[dict]) -> float:
    """Columns that encoders make; the categories of a one-hot column aren't known before the fit."""
    out = 0.0
    for e in encoders:
        each = {"onehot": 12, "text": e.get("n_components", 5), "dates": 5, "numeric": 2 if e.get("indicator") else 1}.get(e["kind"], 1)
        out += each * len(e["cols"])
    return out


def propagate(dag: Dag, sources: dict[str, Meta], selectivity: float = 0.5) -> dict[str, Meta]:
    """Rows and columns of every node from those of the sources."""
    out: dict[str, Meta] = {}
    for n in replace(dag, shared=True).nodes():
        first = out[n.inputs[0].key] if n.inputs else sources.get(n.params.get("source"), Meta(1e6, 20))
        if n.op == "READ":
            out[n.key] = replace(first, cols=len(n.params["columns"]) if n.params.get("columns") else first.cols)
        elif n.op == "FILTER":
            out[n.key] = replace(first, rows=first.rows * selectivity)
        elif n.op == "PROJECT":
            out[n.key] = replace(first, cols=len(n.params["columns"]))
        elif n.op == "ASSIGN":
            out[n.key] = replace(first, cols=first.cols + len(n.params["columns"]))
        elif n.op == "APPLY_PREP":
            out[n.key] = replace(first, cols=features_of(n.params["prep"]["encoders"]) + len(n.params["prep"]["carry"]))
        elif n.op in ("MOMENTS", "SOLVE", "FIT_PREP", "FIT_TREES", "SCORE", "SCORE_MOMENTS", "AVERAGE", "BEST"):
            out[n.key] = Meta(1, first.cols)
        elif n.op == "UDF" and n.params["shape"] not in ("map", "row"):
            out[n.key] = replace(first, rows=first.rows * 2)  # unknown: worst case until a sample tells
        else:
            out[n.key] = first
    return out


Binding = dict[str, Implementation]


def select_impls(dag: Dag, registry: Registry, sources: dict[str, Meta], budget: float, *, policy: str = "cost", cached: set[str] = frozenset(), fidelity: str = "full", reload_per_byte: float = 1e-9) -> tuple[Binding, float]:
    """Implementations by node key and the predicted seconds.

    Policies: cost; heuristic, the most native that fits; interpreted, the least.
    """
    whole = replace(dag, shared=True)
    metas = sources if all(n.key in sources for n in whole.nodes()) else propagate(dag, sources)
    best: dict[str, dict[str, tuple[float, Implementation]]] = {}
    users: dict[str, int] = whole.consumers()
    bound: Binding = {}
    total = 0.0
    for n in whole.nodes():
        meta = metas[n.inputs[0].key] if n.inputs else metas[n.key]
        options = [i for i in registry.options(n, meta, fidelity=fidelity) if i.estimate(meta, metas[n.key]).peak_bytes <= budget]
        if not options:
            raise MemoryError(f"no implementation of {n.op} fits in {budget:.0f} bytes")
        if policy in ("heuristic", "interpreted"):
            bound[n.key] = (min if policy == "heuristic" else max)(options, key=lambda i: PREFERENCE.index(i.backend))
            total += bound[n.key].estimate(meta, metas[n.key]).seconds
            continue
        if n.key in cached:
            seconds = metas[n.key].bytes * reload_per_byte
            best[n.key] = {"catalyst": (seconds, Implementation("reload", "catalyst"))}
        else:
            best[n.key] = {}
            for i in sorted(options, key=lambda i: PREFERENCE.index(i.backend)):
                seconds = i.estimate(meta, metas[n.key]).seconds
                for u in n.inputs:
                    move = lambda b: CONVERT_SECONDS_PER_BYTE.get((b, i.backend), 0.0) * metas[u.key].bytes  # noqa: E731, B023
                    # what several users share is charged to the first alone
                    seconds += min((c if users.get(u.key, 1) == 1 else 0.0) + move(b) for b, (c, _) in best[u.key].items())
                if i.backend not in best[n.key] or seconds < best[n.key][i.backend][0]:
                    best[n.key][i.backend] = (seconds, i)
        if users.get(n.key, 0) > 1:
            keep = min(best[n.key].items(), key=lambda kv: kv[1][0])
            best[n.key] = dict([keep])
            total += keep[1][0]
    if policy in ("heuristic", "interpreted"):
        return bound, total

    def settle(n: Node, wanted: str | None) -> None:
        if n.key in bound:
            return
        seconds = lambda kv: kv[1][0] + (CONVERT_SECONDS_PER_BYTE.get((kv[0], wanted), 0.0) * metas[n.key].bytes if wanted else 0.0)
        bound[n.key] = min(best[n.key].items(), key=seconds)[1][1]
        if n.key not in cached:
            for u in n.inputs:
                settle(u, bound[n.key].backend)

    for sink in whole.sinks.values():
        settle(sink, None)
        total += min(c for c, _ in best[sink.key].values())
    return bound, total


def count_boundaries(dag: Dag, bound: Binding) -> int:
    """Edges of the bound plan that cross between the JVM and Python."""
    inside = lambda n: bound[n.key].backend in ("catalyst", "mllib")
    return sum(inside(n) != inside(u) for n in replace(dag, shared=True).nodes() for u in n.inputs if n.key in bound and u.key in bound)
