"""Runs lowered DAGs: sequentially, in processes, in threads, with or without sharing and reuse."""

from __future__ import annotations

import json
import os
import subprocess
import sys
import threading
import time
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import encoders, models
from ..plans import select
from ..plans.ir import Dag, Node
from ..plans.lowering import lower
from ..plans.pipeline import Pipeline, PipelineBatch, fuse, parse_spec, to_spec
from ..plans.rewrite import optimize_logical
from ..plans.schedule import Schedule, plan_schedule
from ..workloads import others
from ..workloads.listing import listing
from . import metadata
from .cache import ReuseCache, mark_candidates, storage_bytes


@dataclass(frozen=True)
class OptFlags:
    """logical: rewrites and sharing; selection: implementations by cost (else the interpreted ones);
    parallel: a schedule of concurrent jobs; reuse: the cache.  ``policy`` is cost or heuristic,
    ``fidelity`` low asks for cheaper forms while exploring."""

    logical: bool = True
    selection: bool = True
    parallel: bool = True
    reuse: bool = True
    policy: str = "cost"
    fidelity: str = "full"


@dataclass
class Prepared:
    df: DataFrame
    features: list[str]


@dataclass
class RunResult:
    trials: list[dict]
    nodes: int
    reads: int
    wall: float
    trace: list = field(default_factory=list)

    def best(self) -> dict:
        return min((t for t in self.trials if t["status"] == "ok"), key=lambda t: (t["value"], t["pipeline_id"]))

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = [(t["pipeline_id"], t["value"], t["status"]) for t in self.trials]
        return spark.createDataFrame(rows, "pipeline_id string, value double, status string")


#: Executions that passed their estimate by this factor, and seconds, make the rest of a run be bound anew.
SURPRISE, SURPRISE_SECONDS = 4.0, 2.0


#: Sources that join tables.
JOINED = {"listing"}


class Executor:
    """Rewrites, lowers, binds, schedules and runs a DAG.

    ``budget`` bounds what concurrent nodes may hold, by their worst-case estimates;
    a plan none of whose implementations fits is infeasible before anything runs.
    """

    def __init__(self, spark: SparkSession, sf_dir: str, flags: OptFlags = OptFlags(), cache: ReuseCache | None = None, workers: int | None = None, *, budget: float | None = None, registry: select.Registry | None = None, stage: str = "explore"):
        self.spark, self.sf_dir, self.flags, self.cache = spark, sf_dir, flags, cache if flags.reuse else None
        self.cores = spark.sparkContext.defaultParallelism
        self.workers, self.stage = workers, stage
        self.budget = budget or storage_bytes(spark)
        self.registry = registry or select.default_registry()
        self.done: dict[object, Future] = {}
        self.bins: dict[object, Future] = {}
        self.lock = threading.Lock()
        self.memory = threading.Condition()
        self.held = 0.0
        self.kept: list[DataFrame | models.Binned] = []
        self.observed: dict[str, float] = {}
        self.bound: select.Binding = {}
        self.ops: dict[str, str] = {}
        self.metas: dict[str, select.Meta] = {}
        self.estimates: dict[str, select.CostEstimate] = {}
        self.marks: set[str] = set()
        self.schedule: Schedule | None = None
        self.replans = 0
        self.best_settings: dict[str, int] = {}

    def plan(self, dag: Dag) -> tuple[Dag, list]:
        trace = []
        if self.flags.logical:
            dag, trace = optimize_logical(dag)
        dag = lower(dag, self._route)
        if self.flags.logical:
            dag, more = optimize_logical(dag)
            trace += more
        return dag, trace

    def bind(self, dag: Dag) -> None:
        """Metadata, implementations, marks and a schedule for a lowered DAG."""
        self.metas = metadata.collect_metadata(dag, self.spark, self.sf_dir)
        self.ops = {n.key: n.op for n in dag.nodes()}
        policy = self.flags.policy if self.flags.selection else "interpreted"
        cached = {n.key for n in dag.nodes() if n.op == "APPLY_PREP" and self.cache is not None and self.cache.has(n)}
        fidelity = self.flags.fidelity if self.stage == "explore" else "full"
        self.bound, _ = select.select_impls(dag, self.registry, self.metas, self.budget, policy=policy, cached=cached, fidelity=fidelity)
        self.estimates = select.estimates_of(dag, self.bound, self.metas)
        if self.cache is not None:
            seconds = {k: e.seconds for k, e in self.estimates.items()}
            self.marks = set(mark_candidates(dag, seconds, {k: m.bytes for k, m in self.metas.items()}, self.stage))
        if self.flags.parallel:
            self.schedule = plan_schedule(dag, self.estimates, self.budget, self.cores, self.flags.policy)

    def _route(self, n: Node) -> list[dict]:
        df = self._value(n.inputs[0], "route", {})
        return encoders.route(df, n.params["columns"])

    def run(self, dag: Dag, stage: str | None = None) -> RunResult:
        """Every sink's value; a sink that fails is a trial with a status, the others go on."""
        began = time.time()
        self.stage = stage or self.stage
        dag, trace = self.plan(dag)
        try:
            self.bind(dag)
        except MemoryError:  # bind what fits, a sink at a time
            return self._run_apart(dag, trace, began)
        users = dag.consumers() if dag.shared else {}
        names = list(dag.sinks)

        def one(name: str) -> dict:
            if self.flags.parallel:
                self.spark.sparkContext.setLocalProperty("spark.scheduler.pool", name)
            start = time.time()
            try:
                own = users if dag.shared else Dag({name: dag.sinks[name]}, True).consumers()  # a copy's users are its sink's
                value, status = self._value(dag.sinks[name], name, own), "ok"
            except MemoryError:
                value, status = None, "infeasible"
            except Exception as e:  # one pipeline's failure stays its own
                value, status = None, f"failed: {type(e).__name__}"
            return {"pipeline_id": name, "value": value, "status": status, "seconds": time.time() - start}

        if self.flags.parallel and dag.shared and self.schedule is not None:
            nodes = {n.key: n for n in dag.nodes()}
            with ThreadPoolExecutor(self.workers or max(2, self.schedule.width)) as pool:
                needed = self._needed(dag)
                for key in self.schedule.order:  # inputs come first, so a waiting thread's inputs are running or done
                    if key in needed:
                        pool.submit(inheritable_thread_target(self._ahead), nodes[key], users)
            trials = [one(n) for n in names]
        elif self.flags.parallel and len(names) > 1:
            with ThreadPoolExecutor(self.workers or max(2, min(8, self.cores // 2))) as pool:
                trials = list(pool.map(inheritable_thread_target(one), names))
        else:
            trials = [one(n) for n in names]
        for df in self.kept:
            df.unpersist()
        self.kept.clear()
        self.bins.clear()
        if self.cache is not None:
            self.cache.settle()
        return RunResult(trials, dag.count(), dag.count("READ"), time.time() - began, trace)

    def _needed(self, dag: Dag) -> set[str]:
        """Nodes that a run must look at: nothing below what the cache has."""
        todo, out = list(dag.sinks.values()), set()
        while todo:
            n = todo.pop()
            if n.key not in out:
                out.add(n.key)
                if self.cache is None or not self.cache.has(n):
                    todo += n.inputs
        return out

    def _run_apart(self, dag: Dag, trace: list, began: float) -> RunResult:
        trials = []
        for name, sink in dag.sinks.items():
            alone = Dag({name: sink}, dag.shared)
            try:
                self.bind(alone)
            except MemoryError:
                trials.append({"pipeline_id": name, "value": None, "status": "infeasible", "seconds": 0.0})
                continue
            try:
                value, status = self._value(sink, name, {}), "ok"
            except MemoryError:
                value, status = None, "infeasible"
            except Exception as e:
                value, status = None, f"failed: {type(e).__name__}"
            trials.append({"pipeline_id": name, "value": value, "status": status, "seconds": 0.0})
        return RunResult(trials, dag.count(), dag.count("READ"), time.time() - began, trace)

    def _ahead(self, node: Node, users: dict[str, int]) -> None:
        self.spark.sparkContext.setLocalProperty("spark.scheduler.pool", node.op)
        try:
            self._value(node, "ahead", users)
        except Exception:  # its users meet it again
            pass

    def _value(self, node: Node, sink: str, users: dict[str, int]):
        """The node's value, computed once where nodes are shared, else once for each sink: a copy is a (sink, node) pair."""
        copy = node.key if self.flags.logical else (sink, node.key)
        with self.lock:
            future = self.done.get(copy)
            mine = future is None
            if mine:
                future = self.done[copy] = Future()
        if mine:
            try:
                future.set_result(self._compute(node, sink, users))
            except BaseException as e:
                future.set_exception(e)
        return future.result()

    def _compute(self, n: Node, sink: str, users: dict[str, int]):
        if self.cache is not None and n.op == "APPLY_PREP":
            found = self.cache.probe(n)
            if found is not None:
                return Prepared(*found)
        if self.cache is not None and n.op in ("MOMENTS", "FIT_TREES"):
            state = self.cache.state(n)
            if state is not None:
                return state
        args = [self._value(i, sink, users) for i in n.inputs]
        peak = self.estimates[n.key].peak_bytes if n.key in self.estimates else 0.0
        with self.memory:  # an operator alone may always run: the plan has checked it
            self.memory.wait_for(lambda: not self.held or self.held + peak <= self.budget)
            self.held += peak
        try:
            began = time.time()
            impl = self.bound.get(n.key)
            if impl is not None and impl.run is not None:
                value = impl.run(self, n.params, *args)
                value = Prepared(*value) if n.op == "APPLY_PREP" else value
            else:
                value = getattr(self, f"_{n.op.lower()}")(n.params, *args)
            self.observed[n.key] = time.time() - began
        finally:
            with self.memory:
                self.held -= peak
                self.memory.notify_all()
        self._surprised(n)
        if n.op == "APPLY_PREP":
            if self.cache is not None and n.key in self.marks:
                value = Prepared(self.cache.put(n, value.df, value.features, self.observed[n.key], self.metas[n.key].bytes), value.features)
            elif users.get(n.key, 0) > 1:
                kept, widened = encoders.narrowed(value.df)
                self.kept.append(kept.persist())
                value = Prepared(widened(kept), value.features)
        elif n.op == "READ" and self.flags.logical and users.get(n.key, 0) > 1 and n.params["source"] in JOINED:  # its joins run once for all
            value = value.persist()
            self.kept.append(value)
        if self.cache is not None and n.op in ("MOMENTS", "FIT_TREES"):
            self.cache.put_state(n, value)
        return value

    def binned(self, data: Prepared, rows: DataFrame, train: str, target: str, bins: int) -> models.Binned:
        """The binned training rows of a prepared frame, made once for all fits over them and kept until the run ends."""
        key = (id(data), train, target, bins)
        with self.lock:
            future = self.bins.get(key)
            mine = future is None
            if mine:
                future = self.bins[key] = Future()
        if mine:
            try:
                made = models.Binned(rows, data.features, target, bins)
                made.of = data  # lives as long as its id stands here
                self.kept.append(made)
                future.set_result(made)
            except BaseException as e:
                future.set_exception(e)
        return future.result()

    def _surprised(self, n: Node) -> None:
        """Observed seconds far beyond the estimate replace the constants, and what hasn't run is bound anew."""
        estimate, impl, seconds = self.estimates.get(n.key), self.bound.get(n.key), self.observed[n.key]
        if estimate is None or impl is None or impl.run is None or seconds < SURPRISE_SECONDS or seconds < SURPRISE * estimate.seconds:
            return
        with self.lock:
            self.replan(n)

    def replan(self, after: Node) -> None:
        before = self.metas[after.inputs[0].key] if after.inputs else self.metas[after.key]
        impl, seconds = self.bound[after.key], self.observed[after.key]
        self.registry.calibrate(after.op, impl.name, [(select.Meta(0, 0), 0.1 * seconds), (before, seconds)], safety=1.0)
        options = {i.name: i for i in self.registry.entries.get(after.op, [])}
        for k, own in list(self.bound.items()):  # names are an operator's own: others may have a python_rows too
            if self.ops[k] == after.op and own.run is not None and own.name in options and k not in self.done and k not in self.observed:
                self.bound[k] = options[own.name]
        self.replans += 1

    def estimate_report(self, dag: Dag) -> list[tuple]:
        """(operator, implementation, estimated seconds, observed seconds) of what ran."""
        return [(n.op, self.bound[n.key].name, self.estimates[n.key].seconds, self.observed[n.key]) for n in dag.nodes() if n.key in self.observed and n.key in self.bound]

    def preview(self, node: Node, rows: int = 10) -> list:
        """The eager way out: some rows of a recorded step's frame."""
        dag, _ = self.plan(Dag({"preview": node}))
        self.bind(dag)
        value = self._value(dag.sinks["preview"], "preview", {})
        frame = value.df if isinstance(value, Prepared) else value
        return frame.limit(rows).collect()

    def collect_state(self, node: Node):
        """The eager way out for a fitted step: its state as it is."""
        dag, _ = self.plan(Dag({"state": node}))
        self.bind(dag)
        return self._value(dag.sinks["state"], "state", {})

    # physical operators

    def _read(self, p: dict) -> DataFrame:
        if p["source"] == "listing":
            return listing(self.spark, self.sf_dir, p.get("columns"))
        if p["source"] in others.VIEWS:
            df = others.VIEWS[p["source"]][0](self.spark, self.sf_dir)
        else:
            df = self.spark.read.parquet(f"{self.sf_dir}/{p['source']}.parquet")
        return df.select(*p["columns"]) if p.get("columns") else df

    def _filter(self, p: dict, df: DataFrame) -> DataFrame:
        return df.filter(p["condition"])

    def _project(self, p: dict, df: DataFrame) -> DataFrame:
        return df.select(*p["columns"])

    def _assign(self, p: dict, df: DataFrame) -> DataFrame:
        return df.withColumns({c: F.expr(e) for c, e in p["columns"].items()})

    def _udf(self, p: dict, df: DataFrame) -> DataFrame:
        if p["shape"] == "row":
            return df.withColumn(p["out"], F.udf(p["fn"], p["schema"])(*p["cols"]))
        if p["shape"] == "map":
            return df.mapInPandas(p["fn"], p["schema"] or df.schema)
        return p["fn"](df)

    def _fit_prep(self, p: dict, df: DataFrame) -> dict:
        return encoders.fit_all(df, p["prep"]["encoders"], p["train"], p["target"])

    def _apply_model(self, p: dict, data: Prepared, model: dict) -> DataFrame:
        return models.predicted(data.df, model, data.features)

    def _score(self, p: dict, df: DataFrame) -> float:
        rows, target = df.filter(p["rows"]), p["target"]
        if p["metric"] == "auc":
            return float(models.auc(rows, target, "prediction").first()[0])
        measures = models.regression_measures(target) | models.class_measures(target, "prediction")
        return float(rows.agg(measures[p["metric"]].alias("m")).first()[0])

    def _score_moments(self, p: dict, model: dict, sums: dict) -> float:
        squares, n = models.moment_errors(sums[p["fold"]], model) if p["fold"] in sums else (0.0, 0.0)
        return (squares / n) ** 0.5 if n else float("nan")

    def _average(self, p: dict, *values: float) -> float:
        return float(np.nanmean(values))

    def _best(self, p: dict, *values: float) -> float:
        self.best_settings["best setting"] = int(np.nanargmin(values))
        return float(np.nanmin(values))


NOTHING = OptFlags(False, False, False, False)


def run_sequential(spark: SparkSession, sf_dir: str, *batches: PipelineBatch) -> RunResult:
    """Each pipeline by itself: fresh reads, nothing shared, interpreted operators, one job at a time."""
    began, trials, nodes, reads = time.time(), [], 0, 0
    for p in (p for b in batches for p in b.pipelines):
        spark.catalog.clearCache()
        one = Executor(spark, sf_dir, NOTHING).run(Dag({p.name: p.node}))
        trials += one.trials
        nodes, reads = nodes + one.nodes, reads + one.reads
    return RunResult(trials, nodes, reads, time.time() - began)


def run_thread_parallel(spark: SparkSession, sf_dir: str, *batches: PipelineBatch) -> RunResult:
    """Pipelines as threads without sharing: the process overhead left out."""
    return Executor(spark, sf_dir, OptFlags(False, False, True, False)).run(fuse(*batches))


def run_process_parallel(sf_dir: str, batch: PipelineBatch, workers: int, cores: int, memory: str = "2g") -> RunResult:
    """A process and session for each pipeline, ``workers`` at a time."""
    began = time.time()
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

    def one(p: Pipeline) -> dict:
        told = subprocess.run([sys.executable, "-m", "weftline.runtime.worker", sf_dir, str(max(1, cores // workers)), memory], input=to_spec(p), capture_output=True, text=True, cwd=root)
        if told.returncode:
            return {"pipeline_id": p.name, "value": None, "status": "failed: process", "seconds": 0.0}
        return json.loads(told.stdout.strip().splitlines()[-1])

    with ThreadPoolExecutor(workers) as pool:
        trials = list(pool.map(one, batch.pipelines))
    return RunResult(trials, 0, len(batch.pipelines), time.time() - began)


def run_optimized(spark: SparkSession, sf_dir: str, *batches: PipelineBatch, flags: OptFlags = OptFlags(), cache: ReuseCache | None = None) -> RunResult:
    """One fused DAG under the given optimisations."""
    if flags.reuse and cache is None:
        cache = ReuseCache(spark, sf_dir)
    stage = "exploit" if any(b.stage == "exploit" for b in batches) else "explore"
    return Executor(spark, sf_dir, flags, cache, stage=stage).run(fuse(*batches))


def run_spec(spark: SparkSession, sf_dir: str, spec: str) -> dict:
    p = parse_spec(spec)
    return run_sequential(spark, sf_dir, PipelineBatch((p,))).trials[0]


ABLATION = {
    "sequential": NOTHING, "logical": OptFlags(True, False, False, False), "selection": OptFlags(True, True, False, False),
    "parallel": OptFlags(True, True, True, False), "full": OptFlags(),
}
ISOLATED = {
    "sequential": NOTHING, "logical": OptFlags(True, False, False, False), "selection": OptFlags(False, True, False, False),
    "parallel": OptFlags(False, False, True, False), "reuse": OptFlags(False, False, False, True),
}
