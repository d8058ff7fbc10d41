"""Manifests, what is still to do after an interruption, and lineage cuts in the shared folder."""

from __future__ import annotations

import re
import tempfile

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def shared_root(spark) -> str:
    """The session's ``spark.checkpoint.dir``. Where that is unset, a session of one machine gets a temporary
    folder; on a cluster that is an error, as no executor would see what another one wrote."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = "file://" + tempfile.mkdtemp(prefix="packflow-")
        spark.sparkContext.setCheckpointDir(root)
    root = root if ":" in root.split("/")[0] else f"file://{root}"
    return "file://" + root[5:] if root.startswith("file:/") and not root.startswith("file://") else root


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut lineage through the reliable checkpoint folder."""
    shared_root(df.sparkSession)
    return df.checkpoint()


def pending_partitions(df: DataFrame, manifest: DataFrame) -> DataFrame:
    """Rows whose key has no committed output, the null key included. An anti-join; Spark broadcasts the
    done keys only if it finds them small."""
    done = manifest.select(F.col("part_key").alias("__done")).distinct()
    return df.join(done, F.col("part_key").eqNullSafe(F.col("__done")), "left_anti")


def commit_manifest(manifest: DataFrame, path: str) -> None:
    """Append committed outputs; after all files of them are in place."""
    manifest.write.mode("append").parquet(path)


def run_with_resume(job, max_restarts: int = 3, errors: tuple = (Exception,)):
    """Run ``job(attempt)`` again after a failure; each attempt must skip what the manifest has."""
    for attempt in range(max_restarts + 1):
        try:
            return job(attempt)
        except errors:
            if attempt == max_restarts:
                raise


def redo_bound(policy, n_max: int, inflight: int = 1) -> int:
    """Most texts encoded again after a crash: the open pack and those in flight."""
    return (1 + inflight) * policy.bound(n_max)
