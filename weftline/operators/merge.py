"""Partial results of tasks, merged in parallel before the rest comes to the driver."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Row

#: Partial results that the driver takes at once.
DRIVER_PARTS = 8
#: Bytes of partial results that the driver takes without a round before.
DRIVER_BYTES = 32_000_000


def merged(parts: DataFrame, schema: str, fold: Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]], tasks: int | None = None, size: float = math.inf) -> list[Row]:
    """Rows of ``parts`` folded in rounds, each over the root of the tasks before; all rounds are one job.

    ``tasks`` are those that make the parts, where known, and ``size`` the bytes of
    one's part: few small parts need no round.
    """
    ways = tasks or int(parts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    while ways > DRIVER_PARTS and ways * size > DRIVER_BYTES:
        ways = math.isqrt(ways)
        parts = parts.repartition(ways).mapInPandas(fold, schema)
    return parts.collect()


def summed(parts: DataFrame, tasks: int | None = None, size: float = math.inf) -> dict[int, np.ndarray]:
    """Sums of the arrays ``m`` (doubles as bytes) by ``b``; ``tasks`` and ``size`` as for ``merged``."""

    def fold(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sums: dict[int, np.ndarray] = {}
        for pdf in batches:
            for b, m in zip(pdf["b"], pdf["m"]):
                sums[b] = sums.get(b, 0) + np.frombuffer(m)
        yield pd.DataFrame({"b": list(sums), "m": [m.tobytes() for m in sums.values()]})

    out: dict[int, np.ndarray] = {}
    for r in merged(parts, "b int, m binary", fold, tasks, size):
        out[r["b"]] = out.get(r["b"], 0) + np.frombuffer(r["m"])
    return out
