"""Packing over unbounded input.

``pack_batches`` packs each micro-batch with the online form and records a manifest per batch, so a
replayed batch writes nothing twice; ``CarryingPacker`` carries each lane's unfinished pack on to the next
batch and flushes what waits too long. ``stateful_packs`` keeps each lane's open pack in state between
micro-batches and flushes what waits too long. ``user_day_partitions`` and ``arrival_rates`` are the
event-time side: partitions close when the watermark passes them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from packflow.config import EncoderProfile, PackPolicy
from packflow.operators.encode import stream_pack_encode
from packflow.operators.packing import Packer, greedy_pack
from packflow.operators.resume import checkpointed
from packflow.operators.sizes import arrival_order, lane_of, partition_sizes

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A file stream of events; timestamps without zone become timestamps, as watermarks need."""
    stream = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def user_day_partitions(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Sizes of user-days; a day's row is final once the watermark has passed it."""
    day = events.withWatermark("ts", late).groupBy(F.window("ts", "1 day"), "user_id")
    return day.agg(F.count(F.lit(1)).alias("n_texts")).select(F.concat_ws("\x1f", F.col("user_id").cast("string"), F.to_date("window.start").cast("string")).alias("part_key"), "n_texts")


def arrival_rates(events: DataFrame, length: str = "1 hour", slide: str = "15 minutes", late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", length, slide)).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def user_sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    s = F.session_window("ts", gap)
    return events.withWatermark("ts", late).groupBy(s, "user_id").agg(F.count(F.lit(1)).alias("n_texts")).select("user_id", F.col("session_window.start").alias("start"), "n_texts")


def deduplicated(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def pack_batches(corpus: DataFrame, policy: PackPolicy, profile: EncoderProfile, manifest: str, lanes: int = 4, sink=None):
    """A stream writer whose batches are packed, encoded and recorded under ``batch_id``."""

    def one(batch: DataFrame, batch_id: int) -> None:
        done = stream_pack_encode(batch, policy, profile, lanes, "manifest", sink)
        done.write.mode("overwrite").parquet(f"{manifest}/batch_id={batch_id}")

    return corpus.writeStream.foreachBatch(one)


class CarryingPacker:
    """Packs micro-batches and carries the unfinished pack of each lane on to the next one, so that batches
    of any size give packs that reach the lower threshold. Partitions stay whole within a batch.

    Below ``root`` each batch leaves its packs, its manifest and what it carries under its number, overwritten
    if the batch is run again; the same input gives the same packs. After ``max_wait`` batches without a
    pack a lane's tail is flushed (reason ``timeout``), and ``finish`` flushes what the last batch left.
    """

    def __init__(self, policy: PackPolicy, profile: EncoderProfile, root: str, lanes: int = 4, sink=None, max_wait: int | None = None):
        if policy.oversize != "own":
            raise ValueError("carried partitions stay whole: take oversize='own'")
        self.policy, self.profile, self.root, self.lanes, self.sink, self.max_wait = policy, profile, root, lanes, sink, max_wait

    def at(self, what: str, batch_id: int) -> str:
        return f"{self.root}/{what}/batch={batch_id}"

    def carried(self, spark: SparkSession, batch_id: int) -> DataFrame | None:
        from packflow.operators.sink import any_file

        path = self.at("carry", batch_id)
        return spark.read.schema("part_key string, seq long, text string, waited int").parquet(path) if any_file(path) else None

    def __call__(self, batch: DataFrame, batch_id: int, last: bool = False) -> None:
        spark = batch.sparkSession
        rows = batch.select("part_key", F.col("seq").cast("long").alias("seq"), "text", F.lit(0).alias("waited"))
        before = self.carried(spark, batch_id - 1)
        rows = checkpointed(rows if before is None else rows.unionByName(before.withColumn("waited", F.col("waited") + 1)))
        plan = checkpointed(greedy_pack(arrival_order(partition_sizes(rows)), self.policy, self.lanes))
        waited = rows.groupBy(lane_of(F.col("part_key"), self.lanes).alias("lane")).agg(F.max("waited").alias("waited"))
        timed_out = F.col("waited") >= self.max_wait if self.max_wait is not None else F.lit(False)
        plan = plan.join(waited, "lane").withColumn("open", (F.col("reason") == "final") & ~timed_out & F.lit(not last))
        reason = F.when((F.col("reason") == "final") & F.lit(not last), "timeout").otherwise(F.col("reason"))
        closed = plan.where(~F.col("open")).withColumn("reason", reason)
        closed.groupBy("lane", "pack_id").agg(F.count(F.lit(1)).alias("parts"), F.sum("n").alias("n"), F.max("reason").alias("reason")).write.mode("overwrite").parquet(self.at("packs", batch_id))
        whose = lambda p: F.col("part_key").eqNullSafe(F.col("__key"))
        keys = lambda p: p.select(F.col("part_key").alias("__key")).distinct()
        done = rows.join(keys(closed), whose(closed), "left_semi").drop("waited")
        stream_pack_encode(done, self.policy, self.profile, self.lanes, "manifest", self.sink).write.mode("overwrite").parquet(self.at("manifest", batch_id))
        rows.join(keys(plan.where("open")), whose(plan), "left_semi").write.mode("overwrite").parquet(self.at("carry", batch_id))

    def finish(self, spark: SparkSession, batch_id: int) -> None:
        """Flush what the last batch carried, as a batch of its own."""
        empty = spark.createDataFrame([], "part_key string, seq long, text string")
        self(empty, batch_id, last=True)


PACKS = "lane int, pack_id long, parts int, n long, reason string"


def packing_step(policy: PackPolicy, max_wait_ms: int | None) -> Callable[[tuple, Iterator[pd.DataFrame], GroupState], Iterator[pd.DataFrame]]:
    """What a lane does with its arrivals, or with the time-out of its open pack."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        lane = int(key[0])
        total, parts, pack = state.get if state.exists else (0, 0, 0)
        out = []
        if state.hasTimedOut:
            if parts:
                out.append((lane, pack, parts, total, "timeout"))
            state.update((0, 0, pack + bool(parts)))
        else:
            packer = Packer(policy)
            packer.total = total
            for batch in batches:
                for n in batch.sort_values(["part_key"])["n_texts"].tolist():
                    held = packer.total
                    before, after = packer.add(int(n), int(n))
                    if before:
                        out.append((lane, pack, parts, held, before))
                        held, parts, pack = 0, 0, pack + 1
                    parts += 1
                    if after:
                        out.append((lane, pack, parts, held + int(n), after))
                        parts, pack = 0, pack + 1
            state.update((packer.total, parts, pack))
            if max_wait_ms is not None:
                state.setTimeoutDuration(max_wait_ms)
        yield pd.DataFrame(out, columns=["lane", "pack_id", "parts", "n", "reason"])

    return step


def stateful_packs(sizes: DataFrame, policy: PackPolicy, lanes: int = 4, max_wait_ms: int | None = 60_000) -> DataFrame:
    """Packs from a stream of ``(part_key, n_texts)`` whose partitions are whole: a lane's open pack (its
    total and parts) is state; it closes by the policy, or by ``max_wait_ms`` without arrivals (never, if None)."""
    keyed = sizes.select(lane_of(F.col("part_key"), lanes).alias("lane"), "part_key", F.col("n_texts").cast("long").alias("n_texts"))
    timeout = GroupStateTimeout.NoTimeout if max_wait_ms is None else GroupStateTimeout.ProcessingTimeTimeout
    return keyed.groupBy("lane").applyInPandasWithState(packing_step(policy, max_wait_ms), PACKS, "total long, parts int, pack long", "append", timeout)


def with_segments(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream with static table: each event with its user's market segment."""
    segments = customers.select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    return events.join(segments, "user_id").select("event_id", "segment")


def bought_after_view(views: DataFrame, purchases: DataFrame, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Stream with stream: purchases within a while after a view by the same user; watermarks bound what waits."""
    v = views.withWatermark("ts", late).select(F.col("event_id").alias("view_id"), F.col("user_id").alias("viewer"), F.col("ts").alias("seen"))
    p = purchases.withWatermark("ts", late).select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("buyer"), F.col("ts").alias("bought"))
    return v.join(p, F.expr(f"viewer = buyer and bought >= seen and bought <= seen + interval {within}")).select("view_id", "purchase_id")


def closed_days(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Events of each day, given out once the watermark has passed the day's end; later rows are dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n")).select(F.to_date("window.start").cast("string").alias("day"), "n")
