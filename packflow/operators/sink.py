"""Where outputs go: deterministic paths, atomic writes, retries, background upload, simulated stores."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from concurrent.futures import Future, ThreadPoolExecutor, wait
from urllib.parse import quote

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import Column
from pyspark.sql import functions as F

from packflow.config import RetryPolicy, StorageProfile
from packflow.operators.serialize import vectors_to_arrow


class UploadError(RuntimeError):
    pass


def output_path(root: str, run_id: str, key: str | None, chunk: int = 0) -> str:
    """The path of a partition's file; depends on run, key and chunk alone."""
    name = "__null__" if key is None else quote(key, safe="")
    return f"{root}/run_id={run_id}/part_key={name}/chunk-{chunk:05d}.parquet"


def output_path_expr(root: str, run_id: str, key: Column, chunk: Column) -> Column:
    """The same as a column (blanks are %20, as in paths)."""
    name = F.coalesce(F.regexp_replace(F.url_encode(key), r"\+", "%20"), F.lit("__null__"))
    name = F.regexp_replace(F.regexp_replace(name, r"\*", "%2A"), "%7E", "~")
    return F.concat(F.lit(f"{root}/run_id={run_id}/part_key="), name, F.lit("/chunk-"), F.lpad(chunk.cast("string"), 5, "0"), F.lit(".parquet"))


def partition_table(key: str | None, seqs, texts, matrix: np.ndarray) -> pa.Table:
    """A partition's output: its rows with fixed-size vectors over the pack's buffer."""
    n = len(seqs)
    return pa.table({"part_key": pa.array([key] * n, pa.string()), "seq": pa.array(seqs, pa.int64()), "embedding": vectors_to_arrow(matrix, "fixed")})


def filesystem(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_table(uri: str, table: pa.Table) -> int:
    """Write under this attempt's own name, then rename: readers see whole files only, and a second
    attempt replaces equal bytes."""
    system, path = filesystem(uri)
    system.create_dir(path.rsplit("/", 1)[0], recursive=True)
    temporary = f"{path}.{uuid.uuid4().hex}.tmp"
    with system.open_output_stream(temporary) as out:
        pq.write_table(table, out)
    size = system.get_file_info(temporary).size
    system.move(temporary, path)
    return size


def exists(uri: str) -> bool:
    from pyarrow import fs

    system, path = filesystem(uri)
    return system.get_file_info(path).type == fs.FileType.File


def any_file(uri: str) -> bool:
    """Whether there is anything at or below a place."""
    from pyarrow import fs

    system, path = filesystem(uri)
    return system.get_file_info(path).type != fs.FileType.NotFound


def with_retry(action: Callable[[], object], policy: RetryPolicy, sleep: Callable[[float], None] = time.sleep) -> tuple[object, int]:
    """(result, retries); the last failure is raised, so that nothing is committed silently."""
    for attempt in range(policy.attempts):
        try:
            return action(), attempt
        except Exception as e:
            if attempt == policy.attempts - 1:
                raise UploadError(f"gave up after {policy.attempts} attempts") from e
            sleep(policy.base_seconds * 2**attempt)
    raise AssertionError


class AsyncUploader:
    """Uploads in the background, at most ``max_inflight`` packs at a time; no workers means at once.

    A pack's matrix stays referenced by its uploads until they end, so the cap is part of the memory
    bound: (1 + max_inflight) packs. ``submit`` blocks when the cap is reached; that time is the stall.
    """

    def __init__(self, workers: int = 16, max_inflight: int = 2, retry: RetryPolicy | None = None, sleep: Callable[[float], None] = time.sleep):
        self.pool = ThreadPoolExecutor(workers) if workers else None
        self.max_inflight, self.retry, self.sleep = max_inflight, retry or RetryPolicy(), sleep
        self.packs: list[list[Future]] = []
        self.stall = 0.0
        self.retries = 0
        self.most = 0

    def _run(self, action):
        result, retries = with_retry(action, self.retry, self.sleep)
        self.retries += retries
        return result

    def submit(self, actions: list[Callable[[], object]]) -> None:
        """Upload one pack's partitions."""
        began = time.perf_counter()
        if self.pool is None:
            for action in actions:
                self._run(action)
            self.stall += time.perf_counter() - began
            return
        while len(self.packs) >= self.max_inflight:
            self._finish(self.packs.pop(0))
        self.stall += time.perf_counter() - began
        self.packs.append([self.pool.submit(self._run, a) for a in actions])
        self.most = max(self.most, len(self.packs))

    @staticmethod
    def _finish(futures: list[Future]) -> None:
        wait(futures)
        for f in futures:
            f.result()

    def close(self) -> None:
        began = time.perf_counter()
        while self.packs:
            self._finish(self.packs.pop(0))
        if self.pool is not None:
            self.pool.shutdown()
        self.stall += time.perf_counter() - began


class SimulatedStore:
    """Waits as a profile says, then writes; for live overlap runs."""

    def __init__(self, profile: StorageProfile, sleep: Callable[[float], None] = time.sleep, seed: int = 0):
        self.profile, self.sleep, self.random = profile, sleep, np.random.default_rng(seed)

    def write(self, uri: str, table: pa.Table) -> int:
        spike = self.profile.spike_ms / 1000 if self.random.random() < self.profile.spike_rate else 0.0
        self.sleep(self.profile.seconds(table.nbytes) + spike)
        return write_table(uri, table)
