"""Logical rewrites over DAGs, each preserving what every sink computes."""

from __future__ import annotations

import ast
import operator
import re
from collections.abc import Callable
from dataclasses import replace

from .ir import Dag, Node

WORD = re.compile(r"'(?:[^']|'')*'|`([^`]+)`|([A-Za-z_]\w*)(\s*\()?")


KEYWORDS = set("AND OR NOT AS CASE WHEN THEN ELSE END IS NULL IN LIKE RLIKE BETWEEN TRUE FALSE INT BIGINT DOUBLE STRING DATE TIMESTAMP INTERVAL DECIMAL".split())


def names_in(expression: str) -> set[str]:
    """Identifiers of a SQL expression that aren't functions or keywords."""
    return {m[1] or m[2] for m in WORD.finditer(expression) if m[1] or m[2] and not m[3] and m[2].upper() not in KEYWORDS}


def cse(dag: Dag) -> Dag:
    """Equal nodes of all sinks become one."""
    return replace(dag, shared=True)


def shared_reads(dag: Dag) -> Dag:
    """Reads of one source with different columns become one read of their union, projected."""
    wanted: dict[str, list] = {}
    for n in dag.nodes():
        if n.op == "READ":
            wanted.setdefault(n.params["source"], []).append(n.params.get("columns"))
    union = {s: None if None in cols else sorted({c for some in cols for c in some}) for s, cols in wanted.items()}

    def change(n: Node) -> Node:
        if n.op != "READ" or n.params.get("columns") == union[n.params["source"]]:
            return n
        whole = Node("READ", {k: v for k, v in n.params.items() if k != "columns"} | ({"columns": union[n.params["source"]]} if union[n.params["source"]] else {}))
        return Node("PROJECT", {"columns": n.params["columns"]}, (whole,)) if n.params.get("columns") else whole

    return dag.mapped(change)


def push_filters(dag: Dag) -> Dag:
    """Filters move below projections, assignments they don't use, and row-local applies.

    An apply keeps its fitted state: the filter never reaches the rows it is fitted on.
    """

    def change(n: Node) -> Node:
        if n.op != "FILTER":
            return n
        below, uses = n.inputs[0], names_in(n.params["condition"])
        made = set(below.params.get("columns", ())) if below.op == "ASSIGN" else set()
        local = below.op in ("PROJECT", "ASSIGN") or below.op == "UDF" and below.params["shape"] == "map" and below.params.get("keeps")
        if below.op == "FILTER":
            merged = " AND ".join(sorted({f"({below.params['condition']})", f"({n.params['condition']})"}))
            return Node("FILTER", {"condition": merged}, below.inputs)
        if local and not uses & made:
            return below.having(inputs=[change(Node("FILTER", n.params, (below.inputs[0],))), *below.inputs[1:]])
        if below.op in ("APPLY_PREP", "APPLY_MODEL") and not uses & {"prediction"} and not any(u.startswith("f_") for u in uses):
            return below.having(inputs=[change(Node("FILTER", n.params, (below.inputs[0],))), *below.inputs[1:]])
        return n

    return dag.mapped(change)


FOLDS = {ast.Add: operator.add, ast.Sub: operator.sub, ast.Mult: operator.mul}
ARITHMETIC = re.compile(r"(?<![\w.'`)])\(?\s*\d+(?:\s*[-+*]\s*\(?\s*\d+\s*\)?)+\s*\)?(?![\w.'`(])")


def fold_constants(dag: Dag) -> Dag:
    """Whole expressions of integers become literals; true conditions and unread constants go.

    Catalyst folds inside a query; this folds parameters, so that equal steps get equal keys.
    """

    def folded(told: str) -> str:
        try:
            tree = ast.parse(told.strip(), mode="eval").body
        except SyntaxError:
            return told

        def value(e: ast.AST) -> int:
            if isinstance(e, ast.Constant) and type(e.value) is int:
                return e.value
            if isinstance(e, ast.BinOp) and type(e.op) in FOLDS:
                return FOLDS[type(e.op)](value(e.left), value(e.right))
            raise ValueError

        try:
            return str(value(tree))
        except ValueError:
            return told

    def change(n: Node) -> Node:
        if n.op == "ASSIGN":
            return n.having(columns={c: folded(e) for c, e in n.params["columns"].items()})
        if n.op == "FILTER" and n.params["condition"].strip().lower() in ("true", "1 = 1"):
            return n.inputs[0]
        return n

    return dag.mapped(change)


def needed_columns(dag: Dag) -> dict[str, set[str] | None]:
    """Columns that users need of each node; None for all."""
    out: dict[str, set[str] | None] = {s.key: None for s in dag.sinks.values()}
    for n in reversed(list(replace(dag, shared=True).nodes())):
        mine = out.get(n.key)
        if n.op == "PROJECT":
            uses = set(n.params["columns"])
        elif n.op == "ASSIGN":
            uses = None if mine is None else (mine - set(n.params["columns"])) | {w for e in n.params["columns"].values() for w in names_in(e)}
        elif n.op == "FILTER":
            uses = None if mine is None else mine | names_in(n.params["condition"])
        elif n.op in ("FIT_PREP", "APPLY_PREP"):
            uses = {c for e in n.params["prep"]["encoders"] for c in e["cols"]} | names_in(n.params["train"]) | {n.params["target"], *n.params["prep"].get("carry", ())}
        else:
            uses = None
        for i in n.inputs:
            before = out.get(i.key, set())
            out[i.key] = None if uses is None or before is None else before | uses
    return out


def prune_columns(dag: Dag) -> Dag:
    """Reads ask for the columns that are used, where every user can tell."""
    need = needed_columns(dag)

    def change(n: Node) -> Node:
        cols = need.get(n.key)
        if n.op == "READ" and cols is not None and "columns" not in n.params:
            return n.having(columns=sorted(cols))
        return n

    return dag.mapped(change)


def collapse_assignments(dag: Dag) -> Dag:
    """A chain of assignments becomes one projection where none reads what another makes."""

    def change(n: Node) -> Node:
        below = n.inputs[0] if n.inputs else None
        if n.op == "ASSIGN" and below.op == "ASSIGN":
            made, mine = below.params["columns"], n.params["columns"]
            if not set(made) & ({w for e in mine.values() for w in names_in(e)} | set(mine)):
                return Node("ASSIGN", {"columns": made | mine}, below.inputs)
        if n.op == "PROJECT" and below.op == "PROJECT":
            return Node("PROJECT", n.params, below.inputs)
        return n

    return dag.mapped(change)


def overwrite_columns(dag: Dag) -> Dag:
    """A version of a column that is replaced before anybody reads it isn't made."""

    def change(n: Node) -> Node:
        below = n.inputs[0] if n.inputs else None
        if n.op == "ASSIGN" and below.op == "ASSIGN":
            read = {w for e in n.params["columns"].values() for w in names_in(e)}
            dead = {c for c in below.params["columns"] if c in n.params["columns"] and c not in read}
            if dead:
                left = {c: e for c, e in below.params["columns"].items() if c not in dead}
                return n.having(inputs=[Node("ASSIGN", {"columns": left}, below.inputs) if left else below.inputs[0]])
        return n

    return dag.mapped(change)


def traced(fn: Callable, cols: list[str] | None = None) -> str | None:
    """SQL for a function of columns (arithmetic, comparisons, if-else, look-ups), else None.

    Parameters stand for ``cols`` in their order (by default for columns of their
    own names); names from outside become the values that they have now.  The
    function's own code says which lambda of a source line it is.
    """
    import inspect
    import textwrap

    try:
        told = textwrap.dedent(inspect.getsource(fn)).strip()
        names = list(inspect.signature(fn).parameters)
        known = inspect.getclosurevars(fn)
    except (OSError, TypeError, ValueError):
        return None
    body = lambda_of(told, fn)
    cols = cols or names
    if body is None or len(cols) != len(names):
        return None
    column = dict(zip(names, cols))
    outside = {**known.globals, **known.nonlocals}
    signs = {ast.Add: "+", ast.Sub: "-", ast.Mult: "*", ast.Div: "/", ast.Gt: ">", ast.Lt: "<", ast.GtE: ">=", ast.LtE: "<=", ast.Eq: "=", ast.NotEq: "<>"}

    def literal(v: object) -> str:
        if isinstance(v, bool) or not isinstance(v, (int, float, str)):
            raise ValueError
        return "'" + v.replace("'", "''") + "'" if isinstance(v, str) else f"CAST({v!r} AS DOUBLE)" if isinstance(v, float) else repr(v)

    def sql(e: ast.AST) -> str:
        if isinstance(e, ast.Name):
            if e.id in column:
                return column[e.id] if column[e.id].isidentifier() else "`" + column[e.id].replace("`", "``") + "`"
            if e.id in outside:
                return literal(outside[e.id])
            raise ValueError
        if isinstance(e, ast.Constant):
            return literal(e.value)
        if isinstance(e, ast.UnaryOp) and isinstance(e.op, ast.USub):
            return f"(- {sql(e.operand)})"
        if isinstance(e, ast.BinOp) and type(e.op) in signs:
            return f"({sql(e.left)} {signs[type(e.op)]} {sql(e.right)})"
        if isinstance(e, ast.Compare) and len(e.ops) == 1 and type(e.ops[0]) in signs:
            return f"({sql(e.left)} {signs[type(e.ops[0])]} {sql(e.comparators[0])})"
        if isinstance(e, ast.IfExp):
            return f"CASE WHEN {sql(e.test)} THEN {sql(e.body)} ELSE {sql(e.orelse)} END"
        if isinstance(e, ast.Subscript) and isinstance(e.value, ast.Name) and isinstance(outside.get(e.value.id), dict):
            cases = " ".join(f"WHEN {literal(k)} THEN {literal(v)}" for k, v in outside[e.value.id].items())
            return f"CASE {sql(e.slice)} {cases} END"
        raise ValueError

    try:
        return sql(body)
    except ValueError:
        return None


def lambda_of(told: str, fn: Callable) -> ast.AST | None:
    """The body of the lambda in a source line whose code is the function's; None if that can't be told."""
    found = []
    start = told.find("lambda")
    while start >= 0:
        for end in range(len(told), start, -1):
            try:
                tree = ast.parse(told[start:end], mode="eval").body
            except (SyntaxError, ValueError):
                continue
            if isinstance(tree, ast.Lambda):
                found.append((tree, told[start:end]))
                break
        start = told.find("lambda", start + 1)
    free = fn.__code__.co_freevars
    for tree, text in found:
        outer = f"def _({', '.join(free)}):\n return {text}" if free else f"_ = {text}"
        try:
            compiled = compile(outer, "<traced>", "exec")
        except SyntaxError:
            continue
        codes = [c for c in walked(compiled) if c.co_name == "<lambda>"]
        same = lambda c: (c.co_code, c.co_names, c.co_varnames, [k for k in c.co_consts if not isinstance(k, type(c))])
        if any(same(c) == same(fn.__code__) for c in codes[:1]):
            return tree.body
    return None


def walked(code):
    yield code
    for k in code.co_consts:
        if isinstance(k, type(code)):
            yield from walked(k)


def vectorize(dag: Dag) -> Dag:
    """Row functions of recognised forms become expressions."""

    def change(n: Node) -> Node:
        if n.op == "UDF" and n.params["shape"] == "row":
            told = traced(n.params["fn"], n.params.get("cols"))
            if told is not None:
                return Node("ASSIGN", {"columns": {n.params["out"]: told}}, n.inputs)
        return n

    return dag.mapped(change)


def merge_fits(dag: Dag) -> Dag:
    """Fits over one input and training set become one fit that serves them all."""
    groups: dict[tuple, list[Node]] = {}
    for n in replace(dag, shared=True).nodes():
        if n.op == "FIT_PREP":
            groups.setdefault((n.inputs[0].key, n.params["train"], n.params["target"]), []).append(n)
    merged: dict[str, Node] = {}
    for members in groups.values():
        if len(members) > 1:
            encoders, seen = [], set()
            for m in members:
                for e in m.params["prep"]["encoders"]:
                    if (told := repr(sorted(e.items(), key=str))) not in seen:
                        seen.add(told)
                        encoders.append(e)
            whole = members[0].having(prep={"encoders": encoders})
            merged |= {m.key: whole for m in members}
    return dag.mapped(lambda n: merged.get(n.key, n))


RULES: dict[str, Callable[[Dag], Dag]] = {
    "vectorize": vectorize, "fold_constants": fold_constants, "collapse_assignments": collapse_assignments,
    "overwrite_columns": overwrite_columns, "push_filters": push_filters, "shared_reads": shared_reads,
    "prune_columns": prune_columns, "merge_fits": merge_fits, "cse": cse,
}


def optimize_logical(dag: Dag, rules: dict[str, Callable[[Dag], Dag]] | None = None, max_rounds: int = 10) -> tuple[Dag, list[tuple[int, str, int]]]:
    """Rules in order until none changes a sink; the trace has round, rule and nodes left."""
    trace = []
    for at in range(max_rounds):
        before = (dag.shared, {k: n.key for k, n in dag.sinks.items()})
        for name, rule in (rules or RULES).items():
            new = rule(dag)
            if (new.shared, new.sinks) != (dag.shared, dag.sinks):
                trace.append((at, name, new.count()))
            dag = new
        if before == (dag.shared, {k: n.key for k, n in dag.sinks.items()}):
            break
    return dag, trace
