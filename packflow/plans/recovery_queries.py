"""Runs through the sink: interruption and resume, transient failures, background uploads, live ledgers."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packflow.config import STORES, PackPolicy, RetryPolicy
from packflow.functions import models
from packflow.functions.hashing import hash_embed
from packflow.operators import encode
from packflow.operators.faults import FlakySink, PoisonedSink
from packflow.operators.resume import pending_partitions, shared_root
from packflow.operators.sink import SimulatedStore
from packflow.plans import sql
from packflow.plans.packing_queries import DIM, DOC_SUMS, ENCODER
from packflow.plans.registry import query
from packflow.sources.corpora import load_corpus

POLICY = PackPolicy(50, 250)
CHATS = sql.CORPORA["conversation"]
VECTORS = "part_key string, seq long, embedding array<float>"


def fresh_root(spark, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def read_back(spark, root: str, run_id: str) -> DataFrame:
    """All vectors that a run's files hold."""
    return spark.read.schema(VECTORS).option("recursiveFileLookup", "true").option("pathGlobFilter", "chunk-*.parquet").parquet(f"{root}/run_id={run_id}")


def recovered_sums(back: DataFrame, corpus: DataFrame) -> DataFrame:
    """The encoder's integer checksums from stored vectors, by the norm that each text's squares give."""
    norms = hash_embed(corpus, DIM, "part_key", "seq").select("part_key", "seq", F.col("squares").alias("expected"))
    counts = F.transform("embedding", lambda x: F.round(x.cast("double") * F.sqrt(F.col("expected").cast("double"))).cast("long"))
    v = back.join(norms, ["part_key", "seq"]).withColumn("v", counts)
    total = lambda f: F.aggregate(F.transform("v", f), F.lit(0).cast("long"), lambda a, x: a + x)
    return v.select("part_key", "seq", total(lambda x, i: x * (i + 1)).alias("weighted"), total(lambda x: x * x).alias("squares"), total(lambda x: (x != 0).cast("long")).alias("touched"))


@query("per_partition_async", DOC_SUMS)
def per_partition_async(spark, sf_dir):
    """A call a partition with uploads in the background, read back from the files."""
    corpus, root = load_corpus(spark, sf_dir, "lang_source"), fresh_root(spark, "own")
    encode.per_partition_encode(corpus, ENCODER, "manifest", encode.PartitionFiles(root, "r1"), "async").write.parquet(f"{root}/manifest")
    return recovered_sums(read_back(spark, root, "r1"), corpus)


@query("stream_pack_sync_equals_async", f"select count(*)::bigint as texts, count(distinct part_key)::bigint as parts, 0::bigint as differing from ({CHATS})")
def stream_pack_sync_equals_async(spark, sf_dir):
    """Files of the synchronous and of the asynchronous form, row against row."""
    corpus, out = load_corpus(spark, sf_dir, "conversation"), []
    for io in ("sync", "async"):
        root = fresh_root(spark, io)
        encode.stream_pack_encode(corpus, POLICY, ENCODER, 4, "manifest", encode.PartitionFiles(root, "r1"), io).write.parquet(f"{root}/manifest")
        out.append(read_back(spark, root, "r1").select("part_key", "seq", F.xxhash64("embedding").alias(f"h_{io}")))
    differing = F.coalesce(F.sum((~F.col("h_sync").eqNullSafe(F.col("h_async"))).cast("long")), F.lit(0))
    return out[0].join(out[1], ["part_key", "seq"], "full").agg(F.count(F.lit(1)).alias("texts"), F.countDistinct("part_key").alias("parts"), differing.alias("differing"))


@query("resume_after_kill", f"""select count(distinct part_key)::bigint as parts, count(*)::bigint as texts, 0::bigint as lost, 0::bigint as rewritten, 0::bigint as encoded_again, true as first_run_failed from ({CHATS})""")
def resume_after_kill(spark, sf_dir):
    """A run dies in the middle of its packs; a second run takes what has no file yet. All texts are stored
    once, no file of the first run is written again, and no partition that had one is encoded again."""
    from packflow.operators.resume import checkpointed
    from packflow.operators.sink import any_file

    corpus, root = load_corpus(spark, sf_dir, "conversation"), fresh_root(spark, "killed")
    sink, failed = encode.PartitionFiles(root, "r1"), False
    try:
        encode.stream_pack_encode(corpus, POLICY, ENCODER, 4, "manifest", PoisonedSink(sink, 5)).write.format("noop").mode("overwrite").save()
    except Exception:
        failed = True
    found = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "chunk-*.parquet")
    files = lambda: found.load(f"{root}/run_id=r1").select("path", "modificationTime")
    before = checkpointed(files()) if any_file(f"{root}/run_id=r1") else spark.createDataFrame([], "path string, modificationTime timestamp")
    done = before.select(F.url_decode(F.regexp_extract("path", "part_key=([^/]*)/", 1)).alias("part_key"))
    rest = checkpointed(pending_partitions(corpus, done))
    encode.stream_pack_encode(rest, POLICY, ENCODER, 4, "manifest", sink).write.parquet(f"{root}/manifest")
    again = spark.read.parquet(f"{root}/manifest").join(done, "part_key", "left_semi").count()
    back = read_back(spark, root, "r1")
    rewritten = before.join(files(), ["path", "modificationTime"], "left_anti").count()
    lost = corpus.select("part_key", "seq").exceptAll(back.select("part_key", "seq")).count()
    numbers = {"lost": lost, "rewritten": rewritten, "encoded_again": again}
    a = back.agg(F.countDistinct("part_key").alias("parts"), F.count(F.lit(1)).alias("texts"))
    return a.select("parts", "texts", *(F.lit(v).cast("long").alias(k) for k, v in numbers.items()), F.lit(failed).alias("first_run_failed"))


FLAKY = 20


@query("retry_transient", f"""select count(*)::bigint as parts, sum(n_texts)::bigint as texts, sum(2 * (('0x' || substr(md5(part_key), 1, 8))::bigint % {FLAKY} = 0)::int)::bigint as retries from ({sql.sizes('conversation')})""")
def retry_transient(spark, sf_dir):
    """Writes of one partition in twenty fail twice before they succeed; retries bring them all home."""
    corpus, root = load_corpus(spark, sf_dir, "conversation"), fresh_root(spark, "flaky")
    sink = FlakySink(encode.PartitionFiles(root, "r1"), FLAKY, 2)
    led = encode.stream_pack_encode(corpus, POLICY, ENCODER, 4, "ledger", sink, "sync", retry=RetryPolicy(3, 0.0))
    led.write.parquet(f"{root}/ledger")
    retries = spark.read.parquet(f"{root}/ledger").agg(F.sum("retries").alias("retries"))
    stored = read_back(spark, root, "r1").agg(F.countDistinct("part_key").alias("parts"), F.count(F.lit(1)).alias("texts"))
    return stored.crossJoin(F.broadcast(retries)).select("parts", "texts", F.col("retries").cast("long").alias("retries"))


@query("ledger_measures")
def ledger_measures(spark, sf_dir):
    """Live ledgers of three ways through simulated stores: calls and texts, seconds by stage, the share of
    upload time that ran behind calls, the share of time in calls, and cost. Times differ from run to run."""
    corpus, out = load_corpus(spark, sf_dir, "conversation"), []
    for name, store, io in (("packed_sync", "regional", "sync"), ("packed_async", "regional", "async"), ("packed_null", "null", "async")):
        root = fresh_root(spark, name)
        sink = encode.PartitionFiles(root, "r1", SimulatedStore(STORES[store]))
        encode.stream_pack_encode(corpus, POLICY, ENCODER, 4, "ledger", sink, io).write.parquet(f"{root}/ledger")
        waits = STORES[store].base_ms / 1000
        lane = spark.read.parquet(f"{root}/ledger").groupBy("lane").agg(
            F.count(F.lit(1)).alias("calls"), F.sum("n_texts").alias("texts"), F.sum("n_parts").alias("parts"), F.sum("t_encode").alias("encode_s"), F.sum("t_stall").alias("stall_s"),
            (F.max(F.col("t_start") + F.col("t_encode") + F.col("t_serialize") + F.col("t_stall")) - F.min("t_start")).alias("wall_s"),
        )
        a = lane.agg(*(F.sum(c).alias(c) for c in ("calls", "texts", "parts", "encode_s", "stall_s", "wall_s")))
        io_s = F.greatest(F.col("parts") * waits, F.col("stall_s"))
        out.append(a.select(
            F.lit(name).alias("run"), "calls", "texts", "encode_s", "stall_s", "wall_s", models.overlap_ratio_observed(F.col("stall_s"), io_s).alias("hidden"),
            F.least(F.lit(1.0), models.duty_cycle(F.col("encode_s"), F.col("wall_s"))).alias("duty"), models.cost_per_million(F.col("wall_s"), F.col("texts"), 7.30).alias("dollars"),
        ))
    return out[0].unionByName(out[1]).unionByName(out[2])
