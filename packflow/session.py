"""A session with what the engine counts on: UTC, adaptive execution, Arrow, reused Python workers."""

from __future__ import annotations

from pyspark.sql import SparkSession


def build(master: str | None = None, shuffle_partitions: int | None = None, checkpoint_dir: str | None = None, **conf: str) -> SparkSession:
    """Get or create it; on a cluster give the shared checkpoint folder, never a machine's own."""
    b = SparkSession.builder.appName("packflow")
    settings = {
        "spark.sql.session.timeZone": "UTC", "spark.sql.adaptive.enabled": "true", "spark.sql.execution.arrow.pyspark.enabled": "true", "spark.python.worker.reuse": "true",
    } | conf
    if shuffle_partitions:
        settings["spark.sql.shuffle.partitions"] = str(shuffle_partitions)
    if checkpoint_dir:
        settings["spark.checkpoint.dir"] = checkpoint_dir
    return (b.master(master) if master else b).config(map=settings).getOrCreate()
