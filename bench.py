"""Times the headline queries and prints one JSON line.

The fused batch of two preparations by two models runs under each step of the
ablation; ``speedup`` is that of the full system over the sequential agent.  The
two-iteration search (two preparations by four models, then the winner's
hyper-parameters) runs under the full system at the two small scales beside
BENCH_SF_DIR.  BENCH_SF_DIR and BENCH_CPUS choose the tables and the cores;
BENCH_FULL=1 adds the two iterations at BENCH_SF_DIR and under the sequential
agent, and the baseline of processes with its memory.
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from weftline.runtime.executor import ABLATION, Executor, run_process_parallel, run_sequential  # noqa: E402
from weftline.runtime.cache import ReuseCache  # noqa: E402
from weftline.runtime.measures import ResourceTrace  # noqa: E402
from weftline.plans.pipeline import fuse  # noqa: E402
from weftline.queries import QUERIES  # noqa: E402
from weftline.search.loop import two_iterations  # noqa: E402
from weftline.runtime.executor import OptFlags  # noqa: E402
from weftline.session import session  # noqa: E402
from weftline.workloads.listing import fused_four  # noqa: E402

OPERATORS = ("listing_view", "agg_basic", "join_inner", "win_rank", "c3_cv_folds", "e6_target_oof", "e12_gram", "i4_numeric_profile", "w8_churn", "w11_text_features")


def main() -> None:
    sf_dir, cores = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), int(os.environ.get("BENCH_CPUS", "8"))
    spark = session(cores)
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}

    def timed(name: str, fn) -> object:
        began = time.time()
        out = fn()
        times[name] = round(time.time() - began, 3)
        return out

    timed("warm_up", lambda: Executor(spark, sf_dir, ABLATION["parallel"]).run(fuse(fused_four())))
    best = {}
    with ResourceTrace() as trace:
        for step, flags in ABLATION.items():
            cache = ReuseCache(spark, sf_dir) if flags.reuse else None
            run = (lambda: run_sequential(spark, sf_dir, fused_four())) if step == "sequential" else (lambda f=flags, c=cache: Executor(spark, sf_dir, f, c).run(fuse(fused_four())))  # noqa: B023
            best[step] = timed(f"fused_four_{step}", run).best()["value"]
            if flags.reuse:
                timed("fused_four_warm", lambda: Executor(spark, sf_dir, flags, cache).run(fuse(fused_four())))  # noqa: B023
    for name in OPERATORS:
        timed(name, lambda n=name: QUERIES[n](spark, sf_dir).write.format("noop").mode("overwrite").save())
    root, own = os.path.split(os.path.abspath(sf_dir))
    for scale in ("sf0.001", "sf0.01", *([own] if os.environ.get("BENCH_FULL") else [])):
        where = os.path.join(root, scale)
        if os.path.isdir(where):
            first, second = timed(f"two_iterations_full_{scale}", lambda w=where: two_iterations(spark, w, OptFlags()))
            best[f"two_iterations_{scale}"] = min(first.best()["value"], second.best()["value"])
    extra = {}
    if os.environ.get("BENCH_FULL"):
        small = os.path.join(root, "sf0.001")
        timed("two_iterations_sequential_sf0.001", lambda: two_iterations(spark, small))
        with ResourceTrace() as many:
            timed("fused_four_processes", lambda: run_process_parallel(sf_dir, fused_four(), 4, cores))
        extra = {"processes_peak_bytes": many.peak_bytes()}
    print(json.dumps({
        "metric": "fused four pipelines, full system", "value": times["fused_four_full"], "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir),
        "speedup": round(times["fused_four_sequential"] / times["fused_four_full"], 2), "best_rmse": best, "peak_bytes": trace.peak_bytes(), **extra,
    }))


if __name__ == "__main__":
    main()
