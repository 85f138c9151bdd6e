"""Measures of runs: ablations, changed lines, utilisation, size sweeps."""

from __future__ import annotations

import difflib
import os
import threading
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .executor import ABLATION, ISOLATED, NOTHING


def ablate(spark: SparkSession, sf_dir: str, mode: str = "cumulative") -> list[dict]:
    """Seconds, speed-up and best measure for each step, cumulative or each alone."""
    from ..search.loop import two_iterations

    out: list[dict] = []
    for step, flags in {"cumulative": ABLATION, "isolated": ISOLATED}[mode].items():
        began = time.time()
        first, second = two_iterations(spark, sf_dir, None if flags == NOTHING else flags)
        seconds = time.time() - began
        out.append({"step": step, "seconds": seconds, "speedup": out[0]["seconds"] / seconds if out else 1.0, "best": min(first.best()["value"], second.best()["value"]), "nodes": first.nodes, "reads": first.reads})
    return out


def changed_line_ratio(old: str, new: str) -> float:
    """Inserted and deleted lines over all lines of both, by a longest common subsequence."""
    a, b = old.splitlines(), new.splitlines()
    same = sum(m.size for m in difflib.SequenceMatcher(None, a, b, autojunk=False).get_matching_blocks())
    return (len(a) + len(b) - 2 * same) / max(1, len(a) + len(b))


def changed_line_sets(versions: DataFrame, *by: str) -> DataFrame:
    """The set-based form on (version, text), within ``by``: lines that the version before lacks, over its lines."""
    from pyspark.sql import Window

    lines = versions.withColumn("lines", F.array_distinct(F.split("text", "\n")))
    before = F.lag("lines").over(Window.partitionBy(*by).orderBy("version"))
    return lines.withColumn("before", before).filter("before is not null").select(
        *by, "version", F.round(F.size(F.array_except("lines", "before")) / F.size("lines"), 6).alias("changed_ratio")
    )


class ResourceTrace:
    """Samples processor time and memory of this process and its children while it is open."""

    def __init__(self, every: float = 0.2):
        self.every, self.rows, self.over = every, [], threading.Event()

    def __enter__(self) -> "ResourceTrace":
        self.thread = threading.Thread(target=self._sample, daemon=True)
        self.thread.start()
        return self

    def __exit__(self, *_: object) -> None:
        self.over.set()
        self.thread.join()

    def _sample(self) -> None:
        import psutil

        me = psutil.Process(os.getpid())
        while not self.over.wait(self.every):
            procs, cpu, rss = [me, *me.children(recursive=True)], 0.0, 0
            for p in procs:
                try:
                    cpu += sum(p.cpu_times()[:2])
                    rss += p.memory_info().rss
                except psutil.Error:
                    pass
            self.rows.append((time.time(), cpu, rss))

    def peak_bytes(self) -> int:
        return max((r[2] for r in self.rows), default=0)


def utilization(trace: DataFrame, width: str) -> DataFrame:
    """Mean and greatest value of a trace (ts, value) in windows."""
    return trace.groupBy(F.window("ts", width)).agg(F.round(F.avg("value"), 4).alias("mean_value"), F.max("value").alias("max_value"), F.count("*").alias("n")).select(
        F.col("window.start").cast("timestamp_ntz").alias("bucket_start"), "mean_value", "max_value", "n"
    )


def measure_wall(fn: Callable[[], object]) -> tuple[float, object]:
    began = time.time()
    value = fn()
    return time.time() - began, value
