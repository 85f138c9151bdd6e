"""Spark sessions for the engine."""

from __future__ import annotations

from pyspark.sql import SparkSession


def session(cores: int = 8, memory: str = "12g", shuffle_partitions: int | None = None) -> SparkSession:
    """A local session as tests and the bench use it; on a cluster the session is given."""
    return (
        SparkSession.builder.master(f"local[{cores}]").appName("weftline")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions or cores))
        .config("spark.sql.adaptive.enabled", "true").config("spark.scheduler.mode", "FAIR")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false")
        .config("spark.driver.memory", memory).config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
