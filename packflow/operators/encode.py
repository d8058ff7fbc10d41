"""Encode strategies: one call per pack, per partition, per fixed batch, or per planned bin.

All return the same rows ``(part_key, seq, embedding)``, or integer checksums of them, or a manifest of
the files they wrote; they differ in how texts are grouped into encoder calls. Only texts are shuffled
ahead of the encoder, never vectors, except by the fixed-batch baseline, whose regrouping that is.
"""

from __future__ import annotations

import functools
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packflow.config import EncoderProfile, PackPolicy, RetryPolicy
from packflow.functions.hashing import HashEncoder
from packflow.operators.packing import Packer
from packflow.operators.serialize import vectors_to_arrow, vectors_to_arrow_naive
from packflow.operators.sizes import lane_of

VECTORS = "part_key string, seq long, embedding array<float>"
CHECKSUMS = "part_key string, seq long, weighted long, squares long, touched long"
LEDGER = "lane int, pack_id long, reason string, n_parts int, n_texts long, n_bytes long, data_bytes long, t_start double, t_encode double, t_serialize double, t_stall double, retries int, rss_mb double"
MANIFEST = "part_key string, chunk int, lane int, pack_id long, start_off long, end_off long, n_texts long, path string, committed_at double"
SCHEMAS = {"vectors": VECTORS, "checksums": CHECKSUMS, "ledger": LEDGER, "manifest": MANIFEST}


class UnsortedInputError(ValueError):
    """A key came again after another key; it would get two outputs on one path."""


@functools.cache
def get_encoder(profile: EncoderProfile) -> HashEncoder:
    """Started once per Python worker and reused by its tasks."""
    return HashEncoder(profile.dim, profile.work, profile.batch, profile.call_s)


@dataclass
class Unit:
    """A partition or a piece of one, as Arrow slices; texts are not copied until their pack is encoded."""

    key: str | None
    chunk: int
    whole: int
    seqs: list[pa.Array] = field(default_factory=list)
    texts: list[pa.Array] = field(default_factory=list)
    n: int = 0

    def take(self, seqs: pa.Array, texts: pa.Array) -> None:
        self.seqs.append(seqs)
        self.texts.append(texts)
        self.n += len(seqs)


def key_runs(keys: pa.Array) -> Iterator[tuple[str | None, int, int]]:
    """(key, start, end) of each run of equal keys, nulls equal, by comparing the column with itself shifted."""
    n = len(keys)
    if not n:
        return
    codes = keys.dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False)
    cuts = [0, *(np.flatnonzero(codes[1:] != codes[:-1]) + 1).tolist(), n]
    for a, b in zip(cuts, cuts[1:], strict=False):
        yield keys[a].as_py(), a, b


class PackBuffer:
    """The online form of the packing state: a partition's size is known when its key ends.

    Split, a unit of ``b_max`` leaves as soon as one more row of its key arrives, so at most
    ``b_min - 1 + b_max`` rows wait here; the packs equal those planned from sizes.
    """

    def __init__(self, policy: PackPolicy):
        self.policy, self.state = policy, Packer(policy)
        self.held: list[Unit] = []
        self.current: Unit | None = None
        self.rows_of_key = 0
        self.waiting: list[Unit] = []

    def feed(self, key, seqs: pa.Array, texts: pa.Array) -> Iterator[tuple[list[Unit], str]]:
        """Rows of one key; yields the packs that close."""
        if self.current is None or key != self.current.key:
            yield from self.end_key()
            self.current, self.rows_of_key = Unit(key, 0, 0), 0
        top = self.policy.b_max if self.policy.oversize == "split" else None
        at = 0
        while at < len(seqs):
            if top and self.current.n == top:
                self.current.whole = top + 1  # more rows of this key follow: it is oversized
                chunk = self.current.chunk
                yield from self.add(self.current)
                self.current = Unit(key, chunk + 1, top + 1)
            step = len(seqs) - at if not top else min(len(seqs) - at, top - self.current.n)
            self.current.take(seqs.slice(at, step), texts.slice(at, step))
            at += step

    def end_key(self) -> Iterator[tuple[list[Unit], str]]:
        if self.current is not None and self.current.n:
            unit, self.current = self.current, None
            unit.whole = max(unit.whole, unit.n)
            yield from self.add(unit)

    def add(self, unit: Unit) -> Iterator[tuple[list[Unit], str]]:
        before, after = self.state.add(unit.n, unit.whole)
        if before:
            yield self.held, before
            self.held = []
        self.held.append(unit)
        if after:
            yield self.held, after
            self.held = []

    def finish(self) -> Iterator[tuple[list[Unit], str]]:
        yield from self.end_key()
        if self.held:
            yield self.held, "final"
        self.held, self.state = [], Packer(self.policy)


@dataclass
class Emitter:
    """Encodes packs and makes the rows of one kind of output."""

    profile: EncoderProfile
    what: str = "vectors"
    serialize: str = "zero_copy"
    sink: Callable[[Unit, np.ndarray, int], str] | None = None
    io: str = "async"
    workers: int = 16
    max_inflight: int = 2
    retry: RetryPolicy = RetryPolicy()
    bound: int | None = None

    def start(self) -> None:
        from packflow.operators.sink import AsyncUploader

        self.encoder = get_encoder(self.profile)
        self.uploader = AsyncUploader(self.workers if self.io == "async" else 0, self.max_inflight, self.retry) if self.sink else None

    def pack(self, lane: int, number: int, units: list[Unit], reason: str) -> pa.RecordBatch | None:
        n = sum(u.n for u in units)
        if not n:
            return None
        if self.bound is not None and n > self.bound:
            raise MemoryError(f"pack {number} of lane {lane} has {n} texts, over the bound of {self.bound}")
        texts = [t or "" for u in units for part in u.texts for t in part.to_pylist()]
        began = time.time()
        keys = lambda: pa.array([k for u in units for k in [u.key] * u.n], pa.string())
        seqs = lambda: pa.concat_arrays([s for u in units for s in u.seqs])
        if self.what == "checksums":
            columns = self.encoder.checksums(texts)
            self.encoder.calls += 1
            return pa.RecordBatch.from_arrays([keys(), seqs(), *(pa.array(c, pa.int64()) for c in columns)], names=names(CHECKSUMS))
        matrix = self.encoder.encode(texts)
        matrix.flags.writeable = False  # uploads share it
        encoded = time.time()
        if self.what == "vectors" and not self.sink:
            column = vectors_to_arrow(matrix) if self.serialize == "zero_copy" else vectors_to_arrow_naive(matrix)
            return pa.RecordBatch.from_arrays([keys(), seqs(), column], names=names(VECTORS))
        stall, retries, offset, actions, rows = 0.0, 0, 0, [], []
        for u in units:
            part = matrix[offset : offset + u.n]
            if self.sink:
                actions.append(functools.partial(self.sink, u, part))
            rows.append((u.key, u.chunk, lane, number, offset, offset + u.n, u.n))
            offset += u.n
        serialized = time.time()
        if self.uploader:
            stall, retries = self.uploader.stall, self.uploader.retries
            self.uploader.submit(actions)
            stall, retries = self.uploader.stall - stall, self.uploader.retries - retries
        if self.what == "ledger":
            n_bytes = sum(len(t.encode()) for t in texts)
            row = (lane, number, reason, len(units), n, n_bytes, n_bytes + matrix.nbytes, began, encoded - began, serialized - encoded, stall, retries, resident_mb())
            return batch_of([row], LEDGER)
        paths = [self.sink.path(u) if self.sink else None for u in units]
        return batch_of([(*r, p, time.time()) for r, p in zip(rows, paths, strict=True)], MANIFEST)

    def close(self) -> None:
        if self.uploader:
            self.uploader.close()


def resident_mb() -> float:
    """Memory that this worker holds now; 0 where the system does not tell."""
    try:
        with open("/proc/self/statm") as f:
            return int(f.read().split()[1]) * 4096 / 1e6
    except OSError:
        return 0.0


TYPES = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "array<float>": pa.list_(pa.float32())}


def names(schema: str) -> list[str]:
    return [f.split()[0] for f in schema.split(", ")]


def batch_of(rows: list[tuple], schema: str) -> pa.RecordBatch:
    fields = [f.split() for f in schema.split(", ")]
    columns = list(zip(*rows, strict=True)) if rows else [[]] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, TYPES[t]) for c, (_, t) in zip(columns, fields, strict=True)], names=[f for f, _ in fields])


class PartitionFiles:
    """Writes each unit to its own path through a store; the resume check passes over what is there."""

    def __init__(self, root: str, run_id: str, store=None, resume: bool = True):
        self.root, self.run_id, self.store, self.resume = root, run_id, store, resume

    def path(self, unit: Unit) -> str:
        from packflow.operators.sink import output_path

        return output_path(self.root, self.run_id, unit.key, unit.chunk)

    def __call__(self, unit: Unit, matrix: np.ndarray) -> str:
        from packflow.operators.sink import exists, partition_table, write_table

        path = self.path(unit)
        if not (self.resume and exists(path)):
            table = partition_table(unit.key, pa.concat_arrays(unit.seqs), None, matrix)
            (self.store.write if self.store else write_table)(path, table)
        return path


def route(df: DataFrame, lanes: int, order: tuple[str, ...] = ("seq",), lane=lane_of) -> DataFrame:
    """The one shuffle: texts to lanes by key, in order within a lane; each lane is a task of its own, and
    the fixed number of partitions keeps adaptive execution from changing that. Texts without ``seq`` come
    in the order of other columns, and the lane numbers them."""
    key = F.col("part_key").cast("string")
    seq = F.col("seq").cast("long") if "seq" in df.columns else F.lit(None).cast("long")
    chosen = df.select(lane(key, lanes).alias("lane"), key.alias("part_key"), seq.alias("seq"), "text", *(c for c in order if c != "seq"))
    return chosen.repartitionById(lanes, "lane").sortWithinPartitions("lane", "part_key", *order).select("lane", "part_key", "seq", "text")


def run_lane(policy: PackPolicy, emitter: Emitter):
    """The worker loop over a lane's Arrow batches: runs of keys, buffer, flush, encode, slice, emit."""

    def run(batches):
        emitter.start()
        lane, buffer, number, seen, count = None, None, 0, set(), 0

        def emit(packs):
            nonlocal number
            for units, reason in packs:
                made = emitter.pack(lane, number, units, reason)
                number += 1
                if made is not None:
                    yield made

        last = object()
        for batch in batches:
            lanes = batch.column(0).to_pylist()
            for key, a, b in key_runs(batch.column(1)):
                if lanes[a] != lane or lanes[b - 1] != lane:
                    if buffer is not None:
                        yield from emit(buffer.finish())
                    lane, buffer, number, seen, last = lanes[a], PackBuffer(policy), 0, set(), object()
                if key != last:
                    if key in seen:
                        raise UnsortedInputError(f"key {key!r} came again")
                    seen.add(key)
                    last, count = key, 0
                seqs = batch.column(2).slice(a, b - a)
                if seqs.null_count:  # the texts are numbered here, from 1
                    seqs = pa.array(np.arange(count + 1, count + 1 + b - a))
                count += b - a
                yield from emit(buffer.feed(key, seqs, batch.column(3).slice(a, b - a)))
        if buffer is not None:
            yield from emit(buffer.finish())
        emitter.close()

    return run


def stream_pack_encode(corpus: DataFrame, policy: PackPolicy, profile: EncoderProfile, lanes: int = 8, what: str = "vectors", sink=None, io: str = "async", serialize: str = "zero_copy", order: tuple[str, ...] = ("seq",), lane=lane_of, **more) -> DataFrame:
    """Streaming two-threshold packing: one call per pack of whole partitions, sliced back by their bounds.

    ``order`` numbers texts that have no ``seq`` yet; ``lane`` deals keys to lanes.
    """
    emitter = Emitter(profile, what, serialize, sink, io, bound=policy.b_max if policy.ceiling == "before" and policy.oversize == "split" else None, **more)
    return route(corpus, lanes, order, lane).mapInArrow(run_lane(policy, emitter), SCHEMAS[what])


def per_partition_encode(corpus: DataFrame, profile: EncoderProfile, what: str = "vectors", sink=None, io: str = "sync") -> DataFrame:
    """The baseline of one call per key."""
    emitter = Emitter(profile, what, "zero_copy", sink, io)

    def encode(table: pa.Table) -> pa.Table:
        table = table.combine_chunks().sort_by("seq")
        emitter.start()
        unit = Unit(table.column("part_key")[0].as_py(), 0, len(table))
        unit.take(table.column("seq").combine_chunks(), table.column("text").combine_chunks())
        made = emitter.pack(0, 0, [unit], "partition")
        emitter.close()
        return pa.Table.from_batches([made])

    narrow = corpus.select(F.col("part_key").cast("string").alias("part_key"), F.col("seq").cast("long").alias("seq"), F.coalesce("text", F.lit("")).alias("text"))
    return narrow.groupBy("part_key").applyInArrow(encode, SCHEMAS[what])


def fixed_batch_encode(corpus: DataFrame, size: int, profile: EncoderProfile, what: str = "vectors") -> DataFrame:
    """The boundary-blind baseline: calls of ``size`` texts within each task, then a second shuffle, of what
    the encoder made, to bring each partition's rows together. Nothing is whole before that shuffle ends."""
    emitter = Emitter(profile, what)

    def encode(batches):
        emitter.start()
        held, n, number = [], 0, 0

        def call(rows, number):
            table = pa.Table.from_batches(rows).combine_chunks()
            units = []
            for key, a, b in key_runs(table.column(0).combine_chunks()):
                u = Unit(key, 0, b - a)
                u.take(table.column(1).combine_chunks().slice(a, b - a), table.column(2).combine_chunks().slice(a, b - a))
                units.append(u)
            return emitter.pack(0, number, units, "fixed")

        for batch in batches:
            at = 0
            while at < batch.num_rows:
                step = min(size - n, batch.num_rows - at)
                held.append(batch.slice(at, step))
                n, at = n + step, at + step
                if n == size:
                    yield call(held, number)
                    held, n, number = [], 0, number + 1
        if n:
            yield call(held, number)

    narrow = corpus.select(F.col("part_key").cast("string").alias("part_key"), F.col("seq").cast("long").alias("seq"), F.coalesce("text", F.lit("")).alias("text"))
    made = narrow.mapInArrow(encode, SCHEMAS[what])
    return made if what == "ledger" else made.repartition("part_key").sortWithinPartitions("part_key", "seq")


def planned_encode(corpus: DataFrame, plan: DataFrame, profile: EncoderProfile, what: str = "vectors", tasks: int = 8, sink=None, io: str = "sync") -> DataFrame:
    """Encode by a plan of whole partitions, as the size-sorted baseline makes: rows join their pack, gather,
    and each pack is one call."""
    emitter = Emitter(profile, what, "zero_copy", sink, io)
    keyed = plan.select(F.col("part_key").alias("__key"), "pack_id")
    rows = corpus.join(keyed, F.col("part_key").eqNullSafe(F.col("__key"))).select("pack_id", F.col("part_key").cast("string").alias("part_key"), F.col("seq").cast("long").alias("seq"), F.coalesce("text", F.lit("")).alias("text"))
    ordered = rows.repartitionById(tasks, F.pmod("pack_id", F.lit(tasks)).cast("int")).sortWithinPartitions("pack_id", "part_key", "seq")

    def encode(batches):
        emitter.start()
        pack, units = None, []
        for batch in batches:
            packs = batch.column(0).to_numpy(zero_copy_only=False)
            for key, a, b in key_runs(batch.column(1)):
                for low, high in runs(packs[a:b], a):
                    if packs[low] != pack:
                        if units:
                            yield emitter.pack(0, int(pack), units, "planned")
                        pack, units = packs[low], []
                    if not units or units[-1].key != key:
                        units.append(Unit(key, 0, 0))
                    units[-1].take(batch.column(2).slice(low, high - low), batch.column(3).slice(low, high - low))
        if units:
            yield emitter.pack(0, int(pack), units, "planned")
        emitter.close()

    return ordered.mapInArrow(encode, SCHEMAS[what])


def runs(values: np.ndarray, base: int) -> Iterator[tuple[int, int]]:
    cuts = [0, *(np.flatnonzero(values[1:] != values[:-1]) + 1).tolist(), len(values)]
    for a, b in zip(cuts, cuts[1:], strict=False):
        yield base + a, base + b


def encode_udf(profile: EncoderProfile):
    """A plain vectorised function for one-off use; it has no control over packs."""
    from pyspark.sql.types import ArrayType, FloatType

    @F.pandas_udf(ArrayType(FloatType()))
    def encode(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        encoder = get_encoder(profile)
        for part in texts:
            yield pd.Series(list(encoder.encode([t or "" for t in part])))

    return encode

