"""Nodes and DAGs of operators.

A node is immutable and names its operator, parameters and inputs; equal nodes have
equal keys, which is what common sub-plans and reuse are found by.
"""

from __future__ import annotations

import hashlib
import json
import types
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, field, replace
from typing import Any

#: Classes of logical operators; the kind decides which rewrites may pass a node.
SOURCES, ROWWISE = {"READ"}, {"FILTER", "PROJECT", "ASSIGN", "APPLY_PREP", "APPLY_MODEL", "UDF"}
STATES = {"FIT_PREP", "FIT_MODEL", "MOMENTS", "SOLVE", "BIN", "FIT_TREES"}
COMPOSITE = {"AUTO_PREP", "CROSS_VALIDATE", "GRID_SEARCH", "FIT_MODEL"}
RESULTS = {"SCORE", "BEST", "AVERAGE"}


def canonical(value: Any) -> Any:
    """A JSON form in which equal parameters are equal text; types stay apart."""
    if isinstance(value, dict):
        return {str(k): canonical(v) for k, v in sorted(value.items(), key=lambda kv: str(kv[0]))}
    if isinstance(value, (list, tuple)):
        return [canonical(v) for v in value]
    if isinstance(value, bool) or value is None or isinstance(value, str):
        return value
    if isinstance(value, int):
        return {"int": str(value)}
    if isinstance(value, float):
        return {"float": repr(value)}
    if callable(value):
        return {"code": code_identity(value)}
    raise TypeError(f"{type(value).__name__} can't be a parameter")


def code_identity(fn: Callable) -> str | None:
    """What a function computes by, as text; None if that can't be told."""
    code = getattr(fn, "__code__", None)
    if code is None:
        return None

    def told(c: types.CodeType) -> list:
        return [c.co_code.hex(), c.co_names, [told(k) if isinstance(k, types.CodeType) else repr(k) for k in c.co_consts]]

    try:
        closure = [canonical(cell.cell_contents) for cell in fn.__closure__ or ()]
    except (TypeError, ValueError):
        return None
    return json.dumps([told(code), closure, repr(fn.__defaults__)])


@dataclass(frozen=True)
class Node:
    op: str
    params: dict[str, Any] = field(default_factory=dict)
    inputs: tuple["Node", ...] = ()
    seed: int | None = None
    deterministic: bool = True
    version: int = 1

    def __post_init__(self):
        told = json.dumps([self.op, self.version, canonical(self.params), self.seed, self.deterministic, [n.key for n in self.inputs]])
        object.__setattr__(self, "_key", hashlib.sha256(told.encode()).hexdigest())

    @property
    def key(self) -> str:
        """Equal for nodes that compute the same; file contents are left out."""
        return self._key

    def __hash__(self) -> int:
        return hash(self._key)

    def __eq__(self, other: object) -> bool:
        return isinstance(other, Node) and self._key == other._key

    def __bool__(self) -> bool:
        raise TypeError("a recorded step has no truth value: plans hold no control flow")

    def having(self, *, inputs: Iterable["Node"] | None = None, **params: Any) -> "Node":
        return replace(self, inputs=self.inputs if inputs is None else tuple(inputs), params=self.params | params)

    @property
    def cacheable(self) -> bool:
        """Random steps without a seed aren't reused, nor is what comes after them."""
        own = self.deterministic or self.seed is not None
        known = all(code_identity(v) is not None for v in self.params.values() if callable(v))
        return own and known and all(n.cacheable for n in self.inputs)


@dataclass(frozen=True)
class Dag:
    """Sinks by name, and how many nodes stand for one computation.

    Before common sub-plans are merged each sink keeps its own copies, so a copy is
    a (sink, node) pair; ``shared`` says that equal nodes are one.
    """

    sinks: dict[str, Node]
    shared: bool = False

    def nodes(self) -> Iterator[Node]:
        """Inputs before users; each copy once."""
        seen: set = set()
        for name, sink in self.sinks.items():
            stack = [(sink, False)]
            while stack:
                node, ready = stack.pop()
                mark = node.key if self.shared else (name, node.key)
                if mark in seen:
                    continue
                if ready:
                    seen.add(mark)
                    yield node
                else:
                    stack.append((node, True))
                    stack += [(n, False) for n in reversed(node.inputs)]

    def count(self, op: str | None = None) -> int:
        return sum(1 for n in self.nodes() if op in (None, n.op))

    def consumers(self) -> dict[str, int]:
        out: dict[str, int] = {}
        for node in self.nodes():
            for n in node.inputs:
                out[n.key] = out.get(n.key, 0) + 1
        return out

    def mapped(self, change: Callable[[Node], Node]) -> "Dag":
        """Every node rebuilt, inputs first, by ``change``."""
        done: dict[str, Node] = {}

        def rebuilt(node: Node) -> Node:
            if node.key not in done:
                inputs = tuple(rebuilt(n) for n in node.inputs)
                done[node.key] = change(node if inputs == node.inputs else node.having(inputs=inputs))
            return done[node.key]

        return replace(self, sinks={k: rebuilt(v) for k, v in self.sinks.items()})

    def rows(self) -> tuple[list[tuple], list[tuple]]:
        """Nodes and edges, for tables and for explaining."""
        nodes = [(n.key, n.op, json.dumps(canonical(n.params))) for n in self.nodes()]
        return nodes, [(i.key, n.key, k) for n in self.nodes() for k, i in enumerate(n.inputs)]


def validate_acyclic(edges: Iterable[tuple[str, str]]) -> None:
    """Raises on a cycle among named steps, as declarative specifications could have one."""
    after: dict[str, set[str]] = {}
    for a, b in edges:
        after.setdefault(a, set()).add(b)
        after.setdefault(b, set())
    waiting = {n: sum(n in v for v in after.values()) for n in after}
    free = [n for n, k in waiting.items() if not k]
    done = 0
    while free:
        done += 1
        for m in after[free.pop()]:
            waiting[m] -= 1
            if not waiting[m]:
                free.append(m)
    if done < len(after):
        raise ValueError("the steps depend on each other in a circle")
