"""Streaming forms run to the end of a bounded copy of the events, as queries."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from packflow.config import PackPolicy
from packflow.operators.resume import shared_root
from packflow.operators.sink import any_file
from packflow.plans import sql
from packflow.plans.packing_queries import ENCODER
from packflow.plans.registry import query
from packflow.streaming import packers


#: State on executors' disks, not in their heaps.
STATE_STORE = "spark.sql.streaming.stateStore.providerClass"
ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def run_to_end(df, mode: str):
    """Run a stream over all there is and return what it wrote. Executors write the rows to the shared folder;
    none come to the driver. In complete form a batch holds the whole result, so the last one is it."""
    spark = df.sparkSession
    root = f"{shared_root(spark)}/stream-{uuid.uuid4().hex}"
    last = []

    def whole(batch, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/batch-{batch_id}")
        last[:] = [f"{root}/batch-{batch_id}"]

    w = df.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True)
    w = w.foreachBatch(whole) if mode == "complete" else w.format("parquet").option("path", f"{root}/rows")
    before = spark.conf.get(STATE_STORE, None)
    spark.conf.set(STATE_STORE, ROCKSDB)
    try:
        q = w.start()
    finally:
        spark.conf.set(STATE_STORE, before) if before else spark.conf.unset(STATE_STORE)
    q.awaitTermination()
    found = last if mode == "complete" else [p for p in [f"{root}/rows"] if any_file(p)]
    return spark.read.schema(df.schema).parquet(*found) if found else spark.createDataFrame([], df.schema)


def events(spark, sf_dir):
    """The events table in a folder of its own, as a stream; the source's schema is kept."""
    root = f"{shared_root(spark)}/events-{uuid.uuid4().hex}"
    table = spark.read.parquet(f"{sf_dir}/events.parquet")
    table.repartitionByRange(4, "event_id").write.parquet(root)
    return packers.read_events(spark, root, 8)


@query("stream_user_days", "select user_id || chr(31) || strftime(ts, '%Y-%m-%d') as part_key, count(*)::bigint as n_texts from events group by 1")
def stream_user_days(spark, sf_dir):
    """User-days of a stream in update form; the last value of each is its size."""
    out = run_to_end(packers.user_day_partitions(events(spark, sf_dir)), "complete")
    return out.groupBy("part_key").agg(F.max("n_texts").alias("n_texts"))


@query("stream_arrival_rates", """select strftime(start, '%Y-%m-%d %H:%M:%S') as start, count(*)::bigint as n from (
    select unnest([time_bucket(interval 15 minutes, ts) - i * interval 15 minutes for i in [0, 1, 2, 3]]) as start from events) group by 1""")
def stream_arrival_rates(spark, sf_dir):
    out = run_to_end(packers.arrival_rates(events(spark, sf_dir)), "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("stream_sessions", """select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, count(*)::bigint as n_texts from (
    select *, sum(fresh) over (partition by user_id order by ts, event_id) as s from (
        select *, (ts >= lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes or lag(ts) over (partition by user_id order by ts, event_id) is null)::int as fresh from events)) group by user_id, s""")
def stream_sessions(spark, sf_dir):
    out = run_to_end(packers.user_sessions(events(spark, sf_dir)), "complete")
    return out.select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n_texts")


@query("stream_dedup", "select count(*)::bigint as n, count(distinct event_id)::bigint as ids from events")
def stream_dedup(spark, sf_dir):
    """A stream that holds every event twice keeps each once."""
    once = events(spark, sf_dir)
    twice = once.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    return run_to_end(packers.deduplicated(twice, "60 days").select("event_id"), "append").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("event_id").alias("ids"))


@query("stream_pack_batches", "select user_id::varchar as part_key, count(*)::bigint as n_texts from events group by 1")
def stream_pack_batches(spark, sf_dir):
    """Micro-batches packed and recorded; the manifests hold every text once."""
    root = f"{shared_root(spark)}/batches-{uuid.uuid4().hex}"
    corpus = events(spark, sf_dir).select(F.col("user_id").cast("string").alias("part_key"), F.col("event_id").alias("seq"), F.concat_ws(" ", "event_type", "props").alias("text"))
    q = packers.pack_batches(corpus, PackPolicy(500, 2500), ENCODER, f"{root}/manifest").option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{root}/manifest").groupBy("part_key").agg(F.sum("n_texts").alias("n_texts"))


@query("stream_stateful_packs")
def stream_stateful_packs(spark, sf_dir):
    """Packs that close within the stream; each reached the lower threshold and none passed the upper."""
    sizes = events(spark, sf_dir).select(F.col("event_id").cast("string").alias("part_key"), F.lit(1).alias("n_texts"))
    return run_to_end(packers.stateful_packs(sizes, PackPolicy(100, 500), max_wait_ms=None), "append")


@query("stream_static_join", "select event_id, c_mktsegment as segment from events join customer on user_id = c_custkey")
def stream_static_join(spark, sf_dir):
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet")
    return run_to_end(packers.with_segments(events(spark, sf_dir), customers), "append")


@query("stream_stream_join", """select v.event_id as view_id, p.event_id as purchase_id from events v join events p
    on v.user_id = p.user_id and v.event_type = 'view' and p.event_type = 'purchase' and p.ts >= v.ts and p.ts <= v.ts + interval 1 hour""")
def stream_stream_join(spark, sf_dir):
    """Views and the purchases that follow within an hour, as two streams."""
    views, purchases = events(spark, sf_dir).where("event_type = 'view'"), events(spark, sf_dir).where("event_type = 'purchase'")
    return run_to_end(packers.bought_after_view(views, purchases), "append")


def events_in_batches(spark, sf_dir, number, batches: int):
    """The events as a stream of one file a batch; ``number`` tells a row's batch."""
    root = f"{shared_root(spark)}/events-{uuid.uuid4().hex}"
    table = spark.read.parquet(f"{sf_dir}/events.parquet")
    for b in range(batches):
        table.where(number == b).coalesce(1).write.mode("append").parquet(root)
    return packers.read_events(spark, root, 1)


@query("stream_late_rows", """select strftime(ts, '%Y-%m-%d') as day, count(*)::bigint as n from events where event_id % 50 <> 0 group by 1
    having (strptime(day, '%Y-%m-%d') + interval 1 day) <= (select max(ts) - interval 10 minutes from events)""")
def stream_late_rows(spark, sf_dir):
    """Every fiftieth event comes when its day is over: days close without them, and only closed days come
    out. A batch is held against the watermark that stood before the last one, so two batches go ahead."""
    late = F.when(F.col("event_id") % 50 == 0, 2).otherwise(F.col("event_id") % 2)
    return run_to_end(packers.closed_days(events_in_batches(spark, sf_dir, late, 3)), "append")


CARRY_POLICY, CARRY_LANES, CARRY_BATCHES = PackPolicy(300, 1500, oversize="own"), 4, 4
CARRY_LANE = f"coalesce(('0x' || substr(md5(part_key), 1, 8))::bigint % {CARRY_LANES}, 0)::integer"


def carry_sql() -> str:
    """Batch after batch: sizes of what arrived and what was carried, their plan, and the next carry."""
    ctes, outs = [], []
    for b in range(CARRY_BATCHES + 1):
        own = f"select user_id::varchar as part_key, count(*)::bigint as n_texts, 0::bigint as n_bytes from events where event_id % {CARRY_BATCHES} = {b} group by 1"
        before = f" union all select part_key, n as n_texts, 0 from p{b - 1} where reason = 'final'" if b else ""
        ctes.append(f"s{b} as (select part_key, sum(n_texts)::bigint as n_texts, 0::bigint as n_bytes from ({own}{before}) group by part_key)")
        ctes.append(f"p{b} as materialized (select * from {sql.greedy(sql.arrival(f's{b}'), '300', '1500', 'before', 'own', CARRY_LANE)} g)")
        kept = "" if b == CARRY_BATCHES else " where reason <> 'final'"
        outs.append(f"select {b}::bigint as batch, lane, pack_id, count(*)::bigint as parts, sum(n)::bigint as n, max(reason) as reason from p{b}{kept} group by lane, pack_id")
    return "with " + ", ".join(ctes) + " " + " union all ".join(outs)


@query("stream_pack_carry", carry_sql())
def stream_pack_carry(spark, sf_dir):
    """Micro-batches whose unfinished packs go on to the next batch, and the flush at the end: every pack."""
    root = f"{shared_root(spark)}/carry-{uuid.uuid4().hex}"
    stream = events_in_batches(spark, sf_dir, F.col("event_id") % CARRY_BATCHES, CARRY_BATCHES)
    corpus = stream.select(F.col("user_id").cast("string").alias("part_key"), F.col("event_id").alias("seq"), F.concat_ws(" ", "event_type", "props").alias("text"))
    packer = packers.CarryingPacker(CARRY_POLICY, ENCODER, root, CARRY_LANES)
    q = corpus.writeStream.foreachBatch(packer).option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    packer.finish(spark, CARRY_BATCHES)
    return spark.read.parquet(f"{root}/packs").select(F.col("batch").cast("long").alias("batch"), "lane", "pack_id", "parts", "n", "reason")
