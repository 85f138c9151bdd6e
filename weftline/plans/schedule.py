"""When nodes run: list scheduling under a bound on memory, and degrees of parallelism."""

from __future__ import annotations

import heapq
from dataclasses import dataclass, replace

from .ir import Dag
from .select import CostEstimate

TASK_BYTES = 128 << 20


@dataclass(frozen=True)
class Schedule:
    order: list[str]
    starts: dict[str, float]
    width: int
    makespan: float
    peak_bytes: float
    tasks: dict[str, int]


def critical_path(dag: Dag, estimates: dict[str, CostEstimate]) -> dict[str, float]:
    """Longest remaining seconds of each node."""
    nodes = list(replace(dag, shared=True).nodes())
    left = {n.key: estimates[n.key].seconds for n in nodes}
    for n in reversed(nodes):
        for u in n.inputs:
            left[u.key] = max(left[u.key], estimates[u.key].seconds + left[n.key])
    return left


def simulate(dag: Dag, estimates: dict[str, CostEstimate], width: int, budget: float, cores: int) -> Schedule:
    """Starts the ready node of longest remaining path while width and memory allow it."""
    nodes = {n.key: n for n in replace(dag, shared=True).nodes()}
    left = critical_path(dag, estimates)
    waiting = {k: len({u.key for u in n.inputs}) for k, n in nodes.items()}
    users: dict[str, list[str]] = {}
    for k, n in nodes.items():
        for u in {u.key for u in n.inputs}:
            users.setdefault(u, []).append(k)
    ready = [(-left[k], k) for k, w in waiting.items() if not w]
    heapq.heapify(ready)
    running: list[tuple[float, str]] = []
    now, used, peak, starts, order = 0.0, 0.0, 0.0, {}, []
    tasks = {k: assign_tasks(estimates[k], cores, width) for k in nodes}
    while ready or running:
        held = []
        while ready and len(running) < width:
            p, k = heapq.heappop(ready)
            if used + estimates[k].peak_bytes > budget and running:
                held.append((p, k))
                continue
            if estimates[k].peak_bytes > budget:
                raise MemoryError(f"{nodes[k].op} alone passes the budget")
            used += estimates[k].peak_bytes
            peak = max(peak, used)
            starts[k] = now
            order.append(k)
            speed = min(tasks[k], cores / (len(running) + 1)) / cores
            heapq.heappush(running, (now + estimates[k].seconds / max(speed, 1 / cores) / cores, k))
        for h in held:
            heapq.heappush(ready, h)
        now, k = heapq.heappop(running)
        used -= estimates[k].peak_bytes
        for u in users.get(k, ()):
            waiting[u] -= 1
            if not waiting[u]:
                heapq.heappush(ready, (-left[u], u))
    return Schedule(order, starts, width, now, peak, tasks)


def assign_tasks(estimate: CostEstimate, cores: int, width: int) -> int:
    """Tasks of one job, so that all jobs at once don't pass the cores."""
    size = estimate.out_rows * estimate.out_cols * 8
    return int(max(1, min(size / TASK_BYTES or 1, max(1, cores // width)))) if size < TASK_BYTES * cores else max(1, cores // width)


def plan_schedule(dag: Dag, estimates: dict[str, CostEstimate], budget: float, cores: int, policy: str = "cost") -> Schedule:
    """The width of least simulated time; ties go to the smaller one."""
    if policy == "heuristic":
        ready = sum(not n.inputs for n in replace(dag, shared=True).nodes())
        return simulate(dag, estimates, max(1, min(max(ready, 2), cores // 2)), budget, cores)
    widths = [1]
    while widths[-1] * 2 <= cores:
        widths.append(widths[-1] * 2)
    return min((simulate(dag, estimates, w, budget, cores) for w in widths), key=lambda s: (round(s.makespan, 9), s.width))
