"""Helpers shared by the training-data operators."""

from __future__ import annotations

import contextlib
import math
import re
import tempfile
import uuid
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Stands for a null id where ids are compared: nulls sort after every real id.
NULL_ID = 2**63 - 1
#: Narrow rows that a task of a small step takes, a few MB of them; larger steps have as many tasks as the shuffle gives.
ROWS_A_TASK = 1 << 16
#: Bytes of an Arrow batch within ``small_batches``.
ARROW_CONF, ARROW_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", 8 << 20
#: How intermediate tables are written. On a local disk every file starts a process from the JVM that writes it,
#: and so do its checksum file (Parquet's pages have checksums of their own) and the mark of a finished job.
WRITING = {
    "compression": "zstd",
    "mapreduce.fileoutputcommitter.marksuccessfuljobs": "false",
    "fs.file.impl": "org.apache.hadoop.fs.RawLocalFileSystem",
    "fs.file.impl.disable.cache": "true",
}


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession, name: str) -> str:
    """A fresh folder below the cluster's shared folder (``spark.checkpoint.dir``).

    Where that setting is absent, a session of one machine (``local[...]``, as in tests) gets a temporary
    folder, which is also set as the checkpoint folder; on a cluster that is an error, as no executor
    would see what another one wrote.
    """
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not root:
        root = spark.sparkContext.getCheckpointDir()
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = "file://" + tempfile.mkdtemp(prefix="packflow-")
        spark.sparkContext.setCheckpointDir(root)
    root = root if "://" in root or root.startswith("file:") else f"file://{root}"
    if root.startswith("file:/") and not root.startswith("file://"):
        root = "file://" + root[5:]
    return f"{root.rstrip('/')}/packflow/{name}-{uuid.uuid4().hex}"


@contextlib.contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """Arrow batches of about ``ARROW_BYTES`` for what runs inside: a task's JVM and its Python worker each hold one."""
    before = spark.conf.get(ARROW_CONF)
    spark.conf.set(ARROW_CONF, str(ARROW_BYTES))
    try:
        yield
    finally:
        spark.conf.set(ARROW_CONF, before)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Cut lineage: write to the shared folder and read back."""
    spark = df.sparkSession
    path = shared_dir(spark, name)
    df.write.options(**WRITING).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def in_few_tasks(df: DataFrame, rows: int, each: int = ROWS_A_TASK) -> DataFrame:
    """The same rows, the last step in no more tasks, and so files, than ``rows`` fill. Parts of a shuffle may be
    nearly empty, and each file costs a commit and, on a local disk, two processes forked off the executor."""
    return df.coalesce(min(1 << 30, max(1, -(-rows // each))))


def id_or_last(col: str) -> Column:
    return F.coalesce(F.col(col).cast("long"), F.lit(NULL_ID))


def text_bytes(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """Texts of an Arrow column as UTF-8; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return [b or b"" for b in column.cast(pa.binary()).to_pylist()]


def sliced(batches: Iterable[pa.RecordBatch], column: str, max_bytes: int) -> Iterator[pa.RecordBatch]:
    """Cut batches so that each holds about ``max_bytes`` of ``column`` (one row at least)."""
    import pyarrow.compute as pc

    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
        start = total = 0
        for i, n in enumerate(sizes):
            if i > start and total + n > max_bytes:
                yield batch.slice(start, i - start)
                start, total = i, 0
            total += n
        yield batch.slice(start)


def grid(size: int) -> tuple[int, int]:
    """(bytes of a batch, number of buckets) for operators whose batches send a packed row to each bucket.

    Both grow with the root of the table's bytes, so the rows grow in proportion to the table, of a
    kilobyte of text or more each, and a bucket stays as small as that allows: 2 MB up to 8 GB, 23 MB at
    1 TB, 230 MB at 100 TB.
    """
    share = max(2 << 20, math.isqrt(size << 9))
    return max(4 << 20, min(256 << 20, 2 * share)), max(64, -(-size // share))


def storage(uri: str):
    """(file system, path) for a URI of the shared folder, usable on any executor."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_atomically(uri: str, chunks: Iterable[bytes]) -> int:
    """Write to an attempt's own name, then rename; a repeated attempt replaces equal bytes."""
    system, path = storage(uri)
    system.create_dir(path.rsplit("/", 1)[0], recursive=True)
    temporary, total = f"{path}.{uuid.uuid4().hex}.tmp", 0
    with system.open_output_stream(temporary) as out:
        for chunk in chunks:
            out.write(chunk)
            total += len(chunk)
    system.move(temporary, path)
    return total
