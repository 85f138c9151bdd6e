"""Recording pipelines lazily, declaring variants, and specifications as JSON."""

from __future__ import annotations

import itertools
import json
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from typing import Any

from .ir import Dag, Node, validate_acyclic


@dataclass(frozen=True)
class Pipeline:
    """A recorded chain; no call runs anything."""

    node: Node
    name: str = "pipeline"

    @classmethod
    def read(cls, source: str, **options: Any) -> "Pipeline":
        return cls(Node("READ", {"source": source} | options), source)

    def _then(self, op: str, seed: int | None = None, deterministic: bool = True, **params: Any) -> "Pipeline":
        return Pipeline(Node(op, params, (self.node,), seed, deterministic), self.name)

    def select(self, condition: str) -> "Pipeline":
        return self._then("FILTER", condition=condition)

    def project(self, *columns: str) -> "Pipeline":
        return self._then("PROJECT", columns=list(columns))

    def map(self, **columns: str) -> "Pipeline":
        """Columns from SQL expressions over the step before."""
        return self._then("ASSIGN", columns=columns)

    def call(self, fn: Callable, *, deterministic: bool = True, seed: int | None = None, shape: str = "any", out_schema: str | None = None) -> "Pipeline":
        """Any function as a step: ``map`` over Arrow batches or ``any`` over DataFrames."""
        return self._then("UDF", seed, deterministic, fn=fn, shape=shape, schema=out_schema)

    def prepare(self, prep: dict, train: str, target: str) -> "Pipeline":
        """Fits encoders on the rows of ``train`` and applies them to all."""
        fit = Node("FIT_PREP", {"prep": prep, "train": train, "target": target}, (self.node,))
        return Pipeline(Node("APPLY_PREP", {"prep": prep, "train": train, "target": target}, (self.node, fit)), self.name)

    def auto_prepare(self, train: str, target: str, **options: Any) -> "Pipeline":
        return self._then("AUTO_PREP", train=train, target=target, **options)

    def model(self, model: dict, train: str, target: str) -> "Pipeline":
        fit = Node("FIT_MODEL", {"model": model, "train": train, "target": target}, (self.node,))
        return Pipeline(Node("APPLY_MODEL", {"model": model, "target": target}, (self.node, fit)), self.name)

    def score(self, metric: str, rows: str, target: str) -> "Pipeline":
        return self._then("SCORE", metric=metric, rows=rows, target=target)

    def cross_validate(self, model: dict, train: str, target: str, folds: int = 4, fold: str = "fold", metric: str = "rmse") -> "Pipeline":
        return self._then("CROSS_VALIDATE", model=model, train=train, target=target, folds=folds, fold=fold, metric=metric)

    def grid_search(self, grid: list[dict], train: str, target: str, folds: int = 4, fold: str = "fold", metric: str = "rmse") -> "Pipeline":
        return self._then("GRID_SEARCH", grid=grid, train=train, target=target, folds=folds, fold=fold, metric=metric)

    def named(self, name: str) -> "Pipeline":
        return Pipeline(self.node, name)


@dataclass(frozen=True)
class PipelineBatch:
    """Pipelines that an agent gives together; ``stage`` is explore or exploit."""

    pipelines: tuple[Pipeline, ...]
    stage: str = "explore"
    tenant: str | None = None

    def __post_init__(self):
        if self.stage not in ("explore", "exploit"):
            raise ValueError("a stage is explore or exploit")
        if len({p.name for p in self.pipelines}) < len(self.pipelines):
            raise ValueError("pipelines of a batch need names of their own")


def fuse(*batches: PipelineBatch) -> Dag:
    """One DAG with a sink a pipeline; nothing is shared yet."""
    return Dag({p.name if len(batches) == 1 else f"{i}/{p.name}": p.node for i, b in enumerate(batches) for p in b.pipelines})


@dataclass(frozen=True)
class choose:  # noqa: N801  reads as a verb in declarations
    """Alternatives of one stage: label to a function from pipeline to pipeline."""

    name: str
    options: dict[str, Callable[[Pipeline], Pipeline]] = field(default_factory=dict)


def expand_variants(start: Pipeline, stages: Iterable[choose]) -> list[Pipeline]:
    """One pipeline for each combination of alternatives."""
    out = []
    for combination in itertools.product(*[[(s.name, label, f) for label, f in s.options.items()] for s in stages]):
        pipe = start
        for _, _, step in combination:
            pipe = step(pipe)
        out.append(pipe.named("/".join(label for _, label, _ in combination)))
    return out


def to_spec(pipe: Pipeline, indent: int | None = None) -> str:
    """The pipeline as JSON, a step an object, inputs by name."""
    names: dict[str, str] = {}
    steps = []
    for node in Dag({pipe.name: pipe.node}, shared=True).nodes():
        names[node.key] = f"s{len(names)}"
        steps.append({"id": names[node.key], "op": node.op, "inputs": [names[n.key] for n in node.inputs], "params": node.params, "seed": node.seed})
    return json.dumps({"pipeline_id": pipe.name, "nodes": steps, "sink": names[pipe.node.key]}, indent=indent, sort_keys=True)


def parse_spec(told: str) -> Pipeline:
    spec = json.loads(told)
    by_id = {s["id"]: s for s in spec["nodes"]}
    validate_acyclic((i, s["id"]) for s in spec["nodes"] for i in s["inputs"])
    done: dict[str, Node] = {}

    def node(name: str) -> Node:
        if name not in done:
            s = by_id[name]
            done[name] = Node(s["op"], s["params"], tuple(node(i) for i in s["inputs"]), s.get("seed"))
        return done[name]

    return Pipeline(node(spec["sink"]), spec["pipeline_id"])
