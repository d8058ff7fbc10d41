"""Cost, memory, overlap, intensity and fill models.

Most are plain arithmetic and take numbers or columns alike; those that choose between cases come as a
function of numbers and an ``_expr`` of columns. Seconds, bytes and texts throughout; ``c_enc_ms`` is in
milliseconds per text on one worker.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from packflow.config import EncoderProfile, PackPolicy

# -- wall clock -------------------------------------------------------------------------------------


def call_seconds(n, c_ipc, c_enc_ms, workers):
    """Time of one call of n texts."""
    return c_ipc + n * c_enc_ms / 1000.0 / workers


def call_throughput(n, c_ipc, c_enc_ms, workers):
    return n / call_seconds(n, c_ipc, c_enc_ms, workers)


def break_even_size(c_ipc, c_enc_ms, workers):
    """Texts at which a call spends as long on the boundary as on encoding."""
    return c_ipc * workers / c_enc_ms * 1000.0


def ipc_to_compute(parts, texts, c_ipc, c_enc_ms, workers):
    """Boundary time over encoding time with one call per partition."""
    return parts * c_ipc / (texts * c_enc_ms / 1000.0 / workers)


def ipc_time_share(alpha):
    """Share of the boundary in the time of one call per partition."""
    return alpha / (1.0 + alpha)


def wall_seconds(calls, texts, c_ipc, c_enc_ms, workers):
    return calls * c_ipc + texts * c_enc_ms / 1000.0 / workers


def predicted_speedup(alpha, calls, parts):
    """Over one call per partition."""
    return (1.0 + alpha) / (1.0 + alpha * calls / parts)


def wall_seconds_ext(calls, parts, texts, dim, c_ipc, c_enc_ms, workers, c_part=0.0, c_ser_ns=0.0, exposed_io=0.0):
    """The basic model and, apart from it, a price per partition, per serialized value, and exposed I/O."""
    return wall_seconds(calls, texts, c_ipc, c_enc_ms, workers) + parts * c_part + texts * dim * c_ser_ns * 1e-9 + exposed_io


def prediction_error(predicted, measured):
    return F.abs(predicted - measured) / measured if isinstance(predicted, Column) or isinstance(measured, Column) else abs(predicted - measured) / measured


def ipc_count_fraction(sizes: DataFrame, n_star: float) -> DataFrame:
    """Share of partitions under the break-even size."""
    return sizes.agg(F.avg((F.col("n_texts") < n_star).cast("int")).alias("phi"))


#: Above and below these ratios of boundary to encoding time one side rules.
BOUNDARY_RULES, COMPUTE_RULES = 10.0, 0.1


def regime(alpha: float) -> str:
    return "boundary" if alpha > BOUNDARY_RULES else "compute" if alpha < COMPUTE_RULES else "mixed"


def regime_expr(alpha: Column) -> Column:
    return F.when(alpha > BOUNDARY_RULES, "boundary").when(alpha < COMPUTE_RULES, "compute").otherwise("mixed")


def calibrate_two_point(t1, f1, t2, f2, texts, workers):
    """(c_ipc, c_enc_ms) from the wall times of two runs with different numbers of calls."""
    c_ipc = (t1 - t2) / (f1 - f2)
    return c_ipc, (t1 - f1 * c_ipc) * workers / texts * 1000.0


def calibrate_ledger(ledger: DataFrame, workers: int) -> DataFrame:
    """(c_ipc, c_enc_ms, r2) by regression of call times on call sizes."""
    fit = lambda f: F.expr(f"{f}(t_encode, cast(n_texts as double))")
    return ledger.agg(fit("regr_intercept").alias("c_ipc"), (fit("regr_slope") * workers * 1000.0).alias("c_enc_ms"), fit("regr_r2").alias("r2"))


def recommend(phi: float, cv: float) -> str:
    """Equality counts as not greater."""
    if phi > 0.5:
        return "strong" if cv > 1.0 else "beneficial"
    return "moderate" if cv > 1.0 else "optional"


def recommend_expr(phi: Column, cv: Column) -> Column:
    return F.when((phi > 0.5) & (cv > 1.0), "strong").when(phi > 0.5, "beneficial").when(cv > 1.0, "moderate").otherwise("optional")


def cost_per_million(wall, texts, dollars_per_hour):
    return wall * dollars_per_hour / 3600.0 * 1e6 / texts


def worker_efficiency(t_one, t_many, workers):
    """(speedup, efficiency)"""
    return t_one / t_many, t_one / t_many / workers


def gap_closed(baseline, stronger, packed):
    """(share of the gap that the stronger baseline closes, edge that remains)"""
    return (stronger - baseline) / (packed - baseline), packed / stronger - 1.0


# -- memory -----------------------------------------------------------------------------------------


def pack_bytes(n, text_bytes, dim):
    """Texts and float32 vectors of a pack."""
    return n * (text_bytes + 4 * dim)


def memory_bound(policy: PackPolicy, n_max: int, text_bytes: float, dim: int, inflight: int = 1) -> float:
    """Each upload in flight keeps its pack's matrix."""
    return (1 + inflight) * pack_bytes(policy.bound(n_max), text_bytes, dim)


def rss_estimate(n: int, text_bytes: float, dim: int, sequence: int = 128, batch: int = 1024, constant: float = 1.2e9) -> float:
    """Pack bytes, the token ids and masks of a device batch, and what any process holds."""
    return pack_bytes(n, text_bytes, dim) + batch * sequence * 16 + constant


def fixed_batch_bytes(texts, text_bytes, dim, overhead=1.0):
    """The boundary-blind baseline holds everything until the end."""
    return texts * (text_bytes + 4 * dim) * overhead


def max_feasible_n(memory_bytes, text_bytes, dim, overhead=1.0):
    return memory_bytes / ((text_bytes + 4 * dim) * overhead)


def b_max_for_budget(memory_bytes, text_bytes, dim, inflight=1):
    """Largest ceiling whose packs, with those in flight, fit."""
    n = memory_bytes / ((1 + inflight) * (text_bytes + 4 * dim))
    return F.floor(n).cast("long") if isinstance(n, Column) else math.floor(n)


# -- overlap ----------------------------------------------------------------------------------------


def overlap_ratio_model(t_enc, t_ser, t_upl):
    """Share of I/O that encoding hides; without I/O it is 1."""
    io = t_ser + t_upl
    if isinstance(io, Column) or isinstance(t_enc, Column):
        return F.when(io == 0, 1.0).otherwise(1.0 - F.greatest(F.lit(0.0), io - t_enc) / io)
    return 1.0 if io == 0 else 1.0 - max(0.0, io - t_enc) / io


def overlap_ratio_observed(stall, io):
    if isinstance(stall, Column):
        return F.when(io == 0, 1.0).otherwise(1.0 - stall / io)
    return 1.0 if io == 0 else 1.0 - stall / io


def clock_ledger(totals: DataFrame, profile: EncoderProfile, base_ms: float, mb_per_s: float, c_ser_ns: float = 32.0, text_bytes: int = 51, upload_slots: int = 16) -> DataFrame:
    """A simulated-clock ledger: one row per pack, its encode, serialize and upload seconds.

    Partitions upload ``upload_slots`` at a time, each with the store's wait; bytes share its bandwidth.
    """
    n, parts = F.col("n"), F.col("parts")
    data = n * (text_bytes + 4 * profile.dim)
    wire = data / (mb_per_s * 1e6) if mb_per_s else F.lit(0.0)
    return totals.select(
        "*",
        call_seconds(n, profile.c_ipc, profile.c_enc_ms, profile.workers).alias("t_encode"),
        (n * profile.dim * c_ser_ns * 1e-9).alias("t_serialize"),
        (F.ceil(parts / upload_slots) * (base_ms / 1000.0) + wire).alias("t_upload"),
    )


def tree_sums(x: np.ndarray, fanout: int = 16) -> np.ndarray:
    """Running sums by a tree of ``fanout`` branches: the whole nodes before a row, largest first, then single
    values. DuckDB adds a window's doubles in this order, so the last bits are equal, too; they decide whether
    intervals overlap of which one ends where the other begins."""
    if not len(x):
        return x
    whole = len(x) // fanout
    rows = np.append(x, np.zeros((whole + 1) * fanout - len(x))).reshape(-1, fanout)
    node, out = np.zeros(whole), np.empty_like(rows)
    for k in range(fanout):
        node = node + rows[:whole, k]
    before = tree_sums(node, fanout)
    total = np.append(0.0, before)
    for k in range(fanout):
        out[:, k] = total = total + rows[:, k]
    out[:whole, -1] = before
    return out.reshape(-1)[: len(x)]


def pipeline(ledger: DataFrame, *by: str) -> DataFrame:
    """Adds when each pack is encoded and when its I/O ends with one upload slot, in the order of packs:
    end(j) = A(j) + max over i <= j of (ready(i) - A(i - 1)), A the running sum of I/O times."""

    def timed(t: pa.Table) -> pa.Table:
        t = t.sort_by("pack_id")
        encode, serialize, upload = (t.column(c).to_numpy() for c in ("t_encode", "t_serialize", "t_upload"))
        io = serialize + upload
        ready, io_total = tree_sums(encode), tree_sums(io)
        end = io_total + np.maximum.accumulate(ready - (io_total - io))
        for name, column in (("ready", ready), ("io_total", io_total), ("io_end", end)):
            t = t.append_column(name, pa.array(column))
        return t

    schema = ledger.limit(0).select("*", *(F.lit(0.0).alias(c) for c in ("ready", "io_total", "io_end"))).schema
    return ledger.groupBy(*by).applyInArrow(timed, schema)


# -- intensity, fill, reports ---------------------------------------------------------------------------


def compute_intensity(tokenize, transfer, kernel):
    return kernel / (tokenize + transfer + kernel)


def duty_cycle(encode, wall):
    return encode / wall


def utilization_bound(duty, intensity):
    return duty * intensity


def expected_fill(mean: float, sd: float, b_min: float, form: str = "renewal") -> float:
    """Mean pack over ``b_min``: the printed overshoot, or the renewal one, which is half a mean larger."""
    overshoot = sd * sd / (2 * mean) + (mean / 2 if form == "renewal" else 0.0)
    return 1 + overshoot / b_min


def ttfo_model(strategy: str, n_first: float, texts: float, calls: float, c_ipc: float, c_enc_ms: float, workers: int, io: float, regroup: float = 0.0, size_pass: float = 0.0) -> float:
    """Seconds to the first output: of the first partition, of everything, of the largest bin after a pass
    over sizes, or of the first pack."""
    first = call_seconds(n_first, c_ipc, c_enc_ms, workers) + io
    if strategy == "fixed_batch":
        return wall_seconds(calls, texts, c_ipc, c_enc_ms, workers) + regroup + io
    return size_pass + first if strategy == "ffd" else first


def repeat_stats(runs: DataFrame, by: str, value: str) -> DataFrame:
    """Mean, sample deviation and deviation in percent over repeats."""
    return runs.groupBy(by).agg(F.count(F.lit(1)).alias("runs"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd")).withColumn("sd_percent", F.col("sd") / F.col("mean") * 100)


def flush_alerts(ledger: DataFrame, factor: float = 2.0) -> DataFrame:
    """Flushes that took over ``factor`` times the mean of those before in their run."""
    w = Window.partitionBy("run_id").orderBy("t_start", "pack_id").rowsBetween(Window.unboundedPreceding, -1)
    return ledger.withColumn("running_mean", F.avg("t_encode").over(w)).where(F.col("t_encode") > factor * F.col("running_mean"))


def failure_summary(events: DataFrame) -> DataFrame:
    """Attempts, failures, rate and mean recovery by kind."""
    failed = F.col("failed").cast("long")
    return events.groupBy("kind").agg(F.count(F.lit(1)).alias("attempts"), F.sum(failed).alias("failures"), F.avg(failed.cast("double")).alias("rate"), F.avg(F.when(F.col("failed"), F.col("recovery_s"))).alias("recovery_s"))


def tune_threshold(stats: DataFrame, candidates: DataFrame, profile: EncoderProfile, text_bytes: int, memory_bytes: float, ttfo_seconds: float) -> DataFrame:
    """The threshold with the least predicted time among those whose packs fit the memory and whose first
    output is in time; candidates are few, so they are crossed with the one row of statistics."""
    b = F.col("b_min")
    calls = F.ceil(F.col("texts") / b)
    grid = stats.crossJoin(F.broadcast(candidates)).select(
        "b_min", wall_seconds(calls, F.col("texts"), profile.c_ipc, profile.c_enc_ms, profile.workers).alias("wall"),
        (pack_bytes(b + F.col("n_max"), text_bytes, profile.dim) * 2).alias("bytes"), call_seconds(b + F.col("mean"), profile.c_ipc, profile.c_enc_ms, profile.workers).alias("ttfo"),
    )
    fits = grid.where((F.col("bytes") <= memory_bytes) & (F.col("ttfo") <= ttfo_seconds))
    return fits.agg(F.min_by("b_min", F.struct("wall", "b_min")).alias("b_min"), F.min("wall").alias("wall"), F.count(F.lit(1)).alias("feasible"))
