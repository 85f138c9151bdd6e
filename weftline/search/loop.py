"""Searches over pipelines: the two-iteration loop, halving, incremental feedback, refinement."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

from pyspark.sql import SparkSession

from ..plans.ir import Dag, Node
from ..plans.pipeline import Pipeline, PipelineBatch
from ..runtime.cache import ReuseCache
from ..runtime.executor import Executor, OptFlags, RunResult, run_optimized, run_sequential
from ..workloads.listing import iteration_one, iteration_two


def two_iterations(spark: SparkSession, sf_dir: str, flags: OptFlags | None = None, cache: ReuseCache | None = None) -> tuple[RunResult, RunResult]:
    """All combinations, then hyper-parameters of the best one; without flags, sequentially."""
    if flags is None:
        first = run_sequential(spark, sf_dir, iteration_one())
        return first, run_sequential(spark, sf_dir, iteration_two(first.best()["pipeline_id"]))
    if flags.reuse and cache is None:
        cache = ReuseCache(spark, sf_dir)
    first = run_optimized(spark, sf_dir, iteration_one(), flags=flags, cache=cache)
    return first, run_optimized(spark, sf_dir, iteration_two(first.best()["pipeline_id"]), flags=flags, cache=cache)


def halving_plan(m: int, eta: int, min_rows: int, max_rows: int) -> list[tuple[int, int]]:
    """(candidates, rows) of each rung: ⌈m/ηʲ⌉ candidates on η times more rows."""
    out, rung = [], 0
    while True:
        left, rows = math.ceil(m / eta**rung), min(max_rows, min_rows * eta**rung)
        out.append((left, rows))
        if left == 1 or rows == max_rows:
            return out
        rung += 1


def sampled(node: Node, share: float) -> Node:
    """The plan over a nested hash sample of its reads."""
    return Dag({"": node}).mapped(lambda n: Node("FILTER", {"condition": f"(l_orderkey * 7919 + l_linenumber * 31) % 1000 < {int(1000 * share)}"}, (n,)) if n.op == "READ" else n).sinks[""]


def successive_halving(spark: SparkSession, sf_dir: str, batch: PipelineBatch, eta: int = 2, min_share: float = 0.25) -> list[list[dict]]:
    """Trials of each rung; the better ones go on with more rows."""
    left, share, out = list(batch.pipelines), min_share, []
    while True:
        trials = Executor(spark, sf_dir, OptFlags(reuse=False)).run(Dag({p.name: sampled(p.node, share) for p in left})).trials
        out.append(sorted(trials, key=lambda t: (t["value"] is None, t["value"], t["pipeline_id"])))
        if share >= 1 or len(left) == 1:
            return out
        keep = {t["pipeline_id"] for t in out[-1][: math.ceil(len(left) / eta)]}
        left, share = [p for p in left if p.name in keep], min(1.0, share * eta)


def run_incremental(spark: SparkSession, sf_dir: str, batch: PipelineBatch, chunk: int = 2) -> Iterator[dict]:
    """Trials as chunks end; chunks are ordered by shared prefixes and share one cache."""
    cache = ReuseCache(spark, sf_dir)
    pipes = sorted(batch.pipelines, key=lambda p: p.name)
    for k in range(0, len(pipes), chunk):
        yield from run_optimized(spark, sf_dir, PipelineBatch(tuple(pipes[k : k + chunk])), cache=cache).trials


def refine(pipe: Pipeline, op: str, options: list[dict]) -> list[Pipeline]:
    """Variants that differ in one stage; all before it keeps its identity."""
    return [Pipeline(Dag({"": pipe.node}).mapped(lambda n, o=o: n.having(**o) if n.op == op else n).sinks[""], f"{pipe.name}~{k}") for k, o in enumerate(options)]


def run_search(spark: SparkSession, sf_dir: str, policy: str = "plain", on_trial: Callable[[dict], bool] | None = None) -> dict:
    """The best trial under a policy: plain, sampled, halving, multi (two agents, one cache) or restart."""
    if policy == "sampled":
        return min(successive_halving(spark, sf_dir, iteration_one(), eta=1_000, min_share=0.3)[0], key=lambda t: t["value"])
    if policy == "halving":
        return successive_halving(spark, sf_dir, iteration_one())[-1][0]
    if policy == "multi":
        return run_optimized(spark, sf_dir, iteration_one(), iteration_one()).best()
    if policy == "restart":
        for t in run_incremental(spark, sf_dir, iteration_one()):
            if on_trial is not None and on_trial(t):
                return t
    first, second = two_iterations(spark, sf_dir, OptFlags())
    return min((first.best(), second.best()), key=lambda t: t["value"])
